"""One-medians of nodes: by grouped sums on long rows, or for packed nodes in Arrow tasks without a shuffle."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..functions.expressions import distance, gathered, vector_sum
from ..model import MEDIANS, PRACTICAL, Profile

KERNEL_ROWS = 4096


def group_centroids(rows: DataFrame, by: str, w: Column, d: int) -> DataFrame:
    """(by, y): the weighted centre of gravity of each group."""
    sums = rows.groupBy(by).agg(F.sum(w).alias("w_"), *vector_sum(d, lambda i: w * F.get("coords", F.lit(i))))
    return sums.select(by, gathered(d, "w_").alias("y"))


def group_updates(rows: DataFrame, by: str, w: Column, d: int, current: DataFrame, broadcast: bool = False) -> DataFrame:
    """(by, y): one inverse-distance update of the `current(by, y)` iterates.

    A group whose iterate stands on one of its locations has no successor: its y is null.
    """
    current = F.broadcast(current) if broadcast else current
    gap = rows.join(current, by).withColumn("_g", distance("coords", "y", d))
    pull = w / F.when(F.col("_g") > 0, F.col("_g"))
    sums = gap.groupBy(by).agg(F.sum(pull).alias("w_"), F.min("_g").alias("g_"), *vector_sum(d, lambda i: pull * F.get("coords", F.lit(i))))
    return sums.select(by, F.when(F.col("g_") > 0, gathered(d, "w_")).alias("y"))


def median_iterates(realisations: DataFrame, d: int, steps: int) -> DataFrame:
    """(node_id, y0..y<steps>): the centre of gravity and `steps` updates of every node.

    A node of one location keeps it.
    """
    w = F.col("weight") * F.col("prob")
    out = group_centroids(realisations, "node_id", w, d).withColumnRenamed("y", "y0")
    for k in range(steps):
        new = group_updates(realisations, "node_id", w, d, out.select("node_id", F.col(f"y{k}").alias("y")))
        out = out.join(new.withColumnRenamed("y", f"y{k + 1}"), "node_id").withColumn(f"y{k + 1}", F.coalesce(f"y{k + 1}", f"y{k}"))
    return out


def stop_flags(iterates: DataFrame, d: int, steps: int, ratio: float = 0.1) -> DataFrame:
    """Of each node: the step lengths, their ratio after two updates, and whether the step-ratio rule goes on."""
    out = iterates
    for k in range(1, steps + 1):
        out = out.withColumn(f"step{k}", distance(f"y{k}", f"y{k - 1}", d))
    out = out.withColumn("ratio", F.col("step2") / F.when(F.col("step1") > 0, F.col("step1")))
    return out.select("node_id", *(f"step{k}" for k in range(1, steps + 1)), "ratio", F.coalesce(F.col("ratio") <= ratio, F.lit(False)).alias("goes_on"))


def node_spreads(realisations: DataFrame, medians: DataFrame, d: int) -> DataFrame:
    """(node_id, mass, weight, spread): mean distance to the node's own median y, by mass."""
    gap = realisations.join(medians.select("node_id", "y"), "node_id").withColumn("_g", distance("coords", "y", d))
    return gap.groupBy("node_id").agg(F.sum("prob").alias("mass"), F.max("weight").alias("weight"), (F.sum(F.col("prob") * F.col("_g")) / F.sum("prob")).alias("spread"))


def medians_long(realisations: DataFrame, d: int, updates: int = 2) -> DataFrame:
    """(node_id, coords, weight, mass, spread) after a fixed number of updates, in DataFrame operations."""
    y = median_iterates(realisations, d, updates).select("node_id", F.col(f"y{updates}").alias("y"))
    return node_spreads(realisations, y, d).join(y, "node_id").select("node_id", F.col("y").alias("coords"), "weight", "mass", "spread")


def support_medians(realisations: DataFrame, d: int) -> DataFrame:
    """(node_id, loc_id, cost): each node's location of least expected distance to its own distribution."""
    other = realisations.select("node_id", F.col("coords").alias("_c"), F.col("prob").alias("_p"))
    cost = realisations.join(other, "node_id").groupBy("node_id", "loc_id").agg(F.round(F.sum(F.col("_p") * distance("coords", "_c", d)), 9).alias("cost"))
    return cost.groupBy("node_id").agg(F.min(F.struct("cost", "loc_id")).alias("m")).select("node_id", "m.loc_id", "m.cost")


def packed_batches(batches: Iterator[pa.RecordBatch], rows: int = KERNEL_ROWS) -> Iterator[kernels.Block]:
    for batch in batches:
        for k in range(0, batch.num_rows, rows):
            yield kernels.from_arrow(batch.slice(k, rows))


def node_medians(nodes: DataFrame, profile: Profile = PRACTICAL, seed: int = 1) -> DataFrame:
    """The medians of packed nodes with spread, number of updates and status, in one map without a shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in packed_batches(batches):
            y, spread, steps, status = kernels.node_medians(block, profile, seed)
            n, d = y.shape
            lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(y.ravel()))
            yield pa.record_batch({"node_id": pa.array(block.node_id), "coords": lists, "weight": pa.array(block.weight), "mass": pa.array(block.mass), "spread": pa.array(spread), "steps": pa.array(steps, pa.int32()), "status": pa.array(np.array(kernels.STATUS)[status])})

    return nodes.select("node_id", "weight", "mass", "support").mapInArrow(run, MEDIANS)


def median_diagnostics(nodes: DataFrame, profile: Profile = PRACTICAL) -> DataFrame:
    """(status, steps, n, mean_gap, max_gap): the rule's medians against converged ones, as relative excess of cost."""
    from dataclasses import replace

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tight = replace(profile, stop="step_tolerance", max_steps=300)
        for block in packed_batches(batches):
            _, spread, steps, status = kernels.node_medians(block, profile, 1)
            _, least, _, _ = kernels.node_medians(block, tight, 1)
            gap = np.where(least > 0, spread / np.where(least > 0, least, 1) - 1, 0)
            yield pa.record_batch({"status": pa.array(np.array(kernels.STATUS)[status]), "steps": pa.array(steps, pa.int32()), "gap": pa.array(np.maximum(gap, 0))})

    found = nodes.select("node_id", "weight", "mass", "support").mapInArrow(run, "status string, steps int, gap double")
    return found.groupBy("status", "steps").agg(F.count("*").alias("n"), F.avg("gap").alias("mean_gap"), F.max("gap").alias("max_gap"))
