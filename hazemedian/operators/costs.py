"""Costs: assigned, unassigned, given assignment, deterministic; break-downs; coreset error over many centre sets."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..functions.expressions import centre_array, distance, nearest, squared_distance
from .medians import packed_batches

Centres = Sequence[Sequence[float]]


def centre_rows(spark, centres: Centres) -> DataFrame:
    return spark.createDataFrame([(i, [float(v) for v in c]) for i, c in enumerate(centres)], "centre_id int, centre array<double>")


def collected(centres: DataFrame) -> list[list[float]]:
    """Centres as plain lists: k rows by the meaning of k."""
    return [list(x["coords"]) for x in centres.orderBy("centre_id").collect()]


def expected_distance_matrix(realisations: DataFrame, centres: Centres, d: int) -> DataFrame:
    """(node_id, centre_id, expected_distance) of all pairs: nodes in one partial aggregate, centres as a literal."""
    each = F.posexplode(F.transform(centre_array(centres), lambda c: F.col("prob") * distance("coords", c, d))).alias("centre_id", "part")
    return realisations.select("node_id", each).groupBy("node_id", "centre_id").agg(F.sum("part").alias("expected_distance"))


def nearest_centre_nodes(realisations: DataFrame, centres: Centres, d: int, places: int = 9) -> DataFrame:
    """(node_id, centre_id, expected_distance): whole nodes to their expected nearest centre, lowest id on (rounded) ties.

    One aggregate over the node's rows with a sum for each centre; nodes x centres rows never exist.
    """
    sums = [F.sum(F.col("prob") * distance("coords", F.array(*map(F.lit, map(float, c))), d)).alias(f"s{i}") for i, c in enumerate(centres)]
    per = realisations.groupBy("node_id").agg(*sums)
    best = F.array_min(F.array(*(F.struct(F.round(f"s{i}", places).alias("gap"), F.lit(i).alias("centre_id")) for i in range(len(centres)))))
    return per.select("node_id", best.alias("b")).select("node_id", "b.centre_id", F.col("b.gap").alias("expected_distance"))


def assign_nodes(nodes: DataFrame, centres: Centres, places: int = 9) -> DataFrame:
    """The same for packed nodes, with the same rounding: one map, no shuffle; also for a stream of nodes."""
    c, scale = np.asarray(centres, float), 10.0**places

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in packed_batches(batches):
            gap = np.floor(kernels.expected_distances(block, c) * scale + 0.5) / scale
            at = gap.argmin(1)
            yield pa.record_batch({"node_id": pa.array(block.node_id), "centre_id": pa.array(at.astype(np.int32)), "expected_distance": pa.array(gap[np.arange(len(at)), at]), "weight": pa.array(block.weight), "mass": pa.array(block.mass)})

    return nodes.select("node_id", "weight", "mass", "support").mapInArrow(run, "node_id long, centre_id int, expected_distance double, weight double, mass double")


def best_assigned_cost(nodes: DataFrame, centre_sets: dict[int, Centres]) -> DataFrame:
    """(set_id, cost, expected_weight) of packed nodes for several centre sets in one scan."""
    sets = {k: np.asarray(c, float) for k, c in centre_sets.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, weight = dict.fromkeys(sets, 0.0), 0.0
        for block in packed_batches(batches):
            weight += float((block.weight * block.mass).sum())
            for k, c in sets.items():
                total[k] += kernels.assigned_cost(block, c)
        yield pa.record_batch({"set_id": pa.array(list(sets), pa.int32()), "cost": pa.array(list(total.values())), "expected_weight": pa.array([weight] * len(sets))})

    partial = nodes.select("node_id", "weight", "mass", "support").mapInArrow(run, "set_id int, cost double, expected_weight double")
    return partial.groupBy("set_id").agg(F.sum("cost").alias("cost"), F.sum("expected_weight").alias("expected_weight"))


def assigned_cost(realisations: DataFrame, centres: Centres, assignment: DataFrame, d: int) -> DataFrame:
    """One row: the cost of a given assignment(node_id, centre_id)."""
    to = assignment.join(F.broadcast(centre_rows(realisations.sparkSession, centres)), "centre_id")
    return realisations.join(to, "node_id").agg(F.sum(F.col("weight") * F.col("prob") * distance("coords", "centre", d)).alias("cost"))


def unassigned_cost(realisations: DataFrame, centres: Centres, d: int) -> DataFrame:
    """Each realisation goes to its own nearest centre: a lower bound of the assigned cost."""
    gap = nearest("coords", centres, d)["dist"]
    return realisations.agg(F.sum(F.col("weight") * F.col("prob") * gap).alias("cost"))


def kmedian_cost(points: DataFrame, centres: Centres, d: int, weight: Column | None = None) -> DataFrame:
    return points.agg(F.sum((weight if weight is not None else F.lit(1.0)) * nearest("coords", centres, d)["dist"]).alias("cost"))


def kmeans_cost(points: DataFrame, centres: Centres, d: int, weight: Column | None = None) -> DataFrame:
    gap = F.array_min(F.transform(centre_array(centres), lambda c: squared_distance("coords", c, d)))
    return points.agg(F.sum((weight if weight is not None else F.lit(1.0)) * gap).alias("cost"))


def cost_report(costs: DataFrame, by: Sequence[str], kind: str = "rollup") -> DataFrame:
    """Sums of `cost` and counts by grouping sets of `by`; `level` tells the sets apart."""
    grouped = costs.rollup(*by) if kind == "rollup" else costs.cube(*by)
    return grouped.agg(F.sum("cost").alias("cost"), F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))


def coreset_error_profile(nodes: DataFrame, summary: DataFrame, centre_sets: dict[int, Centres]) -> DataFrame:
    """(set_id, cost_full, cost_summary, relative_gap) over centre sets: an empirical check of the summary's error."""
    full, small = best_assigned_cost(nodes, centre_sets), best_assigned_cost(summary, centre_sets)
    both = full.select("set_id", F.col("cost").alias("cost_full")).join(small.select("set_id", F.col("cost").alias("cost_summary")), "set_id")
    return both.withColumn("relative_gap", F.abs(F.col("cost_summary") - F.col("cost_full")) / F.col("cost_full"))
