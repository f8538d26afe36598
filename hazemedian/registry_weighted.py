"""Queries on nodes with unequal weights, chances and absent mass, and the experiments on the wide inputs.

On the nodes of `orders_absent` the three draw masses, the weighted seeds and the weighted medians give different rows, so
that equality with SQL tells them apart.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from . import oracles as o
from .model import LITERAL, PRACTICAL
from .operators import cells as cell_ops
from .operators import centres as centre_ops
from .operators import costs, medians, nodes
from .plans import experiment, summarise
from .registry import _CELL_SQL, _NEAREST, _SMALL, PER_K, QUERIES, SQL, _result_frame, centre_frame, flat, query, rows_of
from .sources import workloads as w
from .sources.tables import kept

D = 4
_REAL = o.ABSENT
_TWICE = ", ".join([o.start(n=D), o.iterate("y0", "y1", n=D), o.iterate("y1", "y2", n=D)])
_MED, _CELLS = o.med(_REAL, D), o.cells(_REAL, D)


def _absent(spark, d):
    return kept(w.order_realisations(spark, d, True), "absent")


def _medians(spark, d):
    return kept(medians.medians_long(_absent(spark, d), D), "medians")


def _cells(spark, d):
    points = _medians(spark, d)
    return kept(cell_ops.assign_cells(points, [c for _, c in centre_ops.seed_centres(points, 3, D)], D), "cells")


@query(f"{_REAL}, {_TWICE} {o.shown('y2', 'node_id', D)}")
def absent_median_step2(spark, d):
    return flat(medians.median_iterates(_absent(spark, d), D, 2), "y2", D, "node_id")


@query(f"{_MED} SELECT node_id, round(mass, 11) AS mass, round(weight, 8) AS weight, round(spread, 6) AS spread FROM med")
def absent_spread(spark, d):
    return medians.medians_long(_absent(spark, d), D).select("node_id", *(F.round(c, n).alias(c) for c, n in (("mass", 11), ("weight", 8), ("spread", 6))))


@query(None)
def absent_seed_locations(spark, d):
    """Location seeds by realisation weight times distance."""
    score = kept(nodes.location_universe(_absent(spark, d)).select(F.col("loc_id").alias("node_id"), "coords", F.col("score").alias("weight")), "universe")
    found = centre_ops.seed_centres(score, 3, D, 1, F.col("weight"))
    return rows_of(spark, [(i, int(k)) for i, (k, _) in enumerate(found)], "centre int, loc_id long")


@query(f"{_MED}, {o.seeds('med', 'node_id', 3, 1, 'weight', n=D)} SELECT CAST(centre AS INTEGER) AS centre, k AS node_id FROM c_0")
def absent_seed_weighted(spark, d):
    found = centre_ops.seed_centres(_medians(spark, d), 3, D, 1, F.col("weight"))
    return rows_of(spark, [(i, int(k)) for i, (k, _) in enumerate(found)], "centre int, node_id long")


def _round(means: bool):
    def f(spark, d):
        points = _medians(spark, d)
        start = [c for _, c in centre_ops.seed_centres(points, 3, D, 2 if means else 1)]
        now = centre_ops.assign_points(points, start, D)
        turn = centre_ops.mean_round if means else centre_ops.median_round
        return centre_frame(spark, turn(now, D, F.col("weight"), start))

    return f


QUERIES["absent_lloyd_median"], QUERIES["absent_lloyd_means"] = _round(False), _round(True)
SQL["absent_lloyd_median"] = f"WITH {_MED}, {o.seeds('med', 'node_id', 3, 1, n=D)}, {o.assigned('med', 'c_0', 'near1', n=D)}, {o.median_round('near1', 'c_0', '1', 'weight', D)} {o.shown('c_1', n=D)}"
_MEANS = f"r1 AS (SELECT centre, {o.means('weight', D)} FROM near1 GROUP BY centre), c_1 AS (SELECT centre, {', '.join(f'coalesce(n.a{i}, o.a{i}) AS a{i}' for i in range(D))} FROM c_0 o LEFT JOIN r1 n USING (centre))"
SQL["absent_lloyd_means"] = f"WITH {_MED}, {o.seeds('med', 'node_id', 3, 2, n=D)}, {o.assigned('med', 'c_0', 'near1', n=D)}, {_MEANS} {o.shown('c_1', n=D)}"


@query(f"{_CELLS} SELECT node_id, {_CELL_SQL} FROM cells")
def absent_ring_cells(spark, d):
    return _cells(spark, d).select("node_id", *cell_ops.CELL)


@query(f"{_CELLS} SELECT {_CELL_SQL}, count(*) AS n, round(sum(weight), 4) AS weight, round(sum(weight * mass), 4) AS expected_weight, round(sum(weight * mass * dist), 4) AS cost FROM cells GROUP BY ALL")
def absent_cell_stats(spark, d):
    s = cell_ops.cell_stats(_cells(spark, d))
    return s.select(*cell_ops.CELL, "n", *(F.round(c, 4).alias(c) for c in ("weight", "expected_weight", "cost")))


_MASSES = {"weight": "weight", "expected_weight": "(weight * mass)", "uniform": "1e0"}


def _draws(kind: str):
    return lambda spark, d: cell_ops.draw_cells(_cells(spark, d), 3, PER_K, draw_mass=kind)


def _weights(spark, d, kind: str):
    cells = _cells(spark, d)
    return cell_ops.reweight(cells, cell_ops.draw_cells(cells, 3, PER_K, draw_mass=kind), kind)


def _reweighted(kind: str):
    return lambda spark, d: _weights(spark, d, kind).withColumn("weight", F.round("weight", 3))


for _kind, _mass in _MASSES.items():
    QUERIES[f"absent_draws_{_kind}"], QUERIES[f"absent_weights_{_kind}"] = _draws(_kind), _reweighted(_kind)
    SQL[f"absent_draws_{_kind}"] = f"WITH {_CELLS}, {o.drawn(_mass)} SELECT {_CELL_SQL}, node_id, copies, draws FROM dr"
    SQL[f"absent_weights_{_kind}"] = f"WITH {_CELLS}, {o.summary(_mass)} SELECT {_CELL_SQL}, node_id, CAST(copies AS INTEGER) AS copies, round(new_weight, 3) AS weight FROM sw"

_FIX = f"{_REAL}, {o.fixed_centres(n=D)}, {o.expected(n=D)}"


@query(f"{_FIX} {_NEAREST}")
def absent_nearest(spark, d):
    real = _absent(spark, d)
    # The second rounding is of the binary product, as SQL's: of nine places, one row in a thousand ends in 500.
    return costs.assign_nodes(nodes.pack(real), w.hash_centres(real, 5)).select("node_id", "centre_id", (F.round(F.col("expected_distance") * 1e6) / 1e6).alias("expected_distance"))


@query(f"{_FIX} SELECT CAST(0 AS INTEGER) AS set_id, round(sum(weight * e), 3) AS cost, round(sum(weight * mass), 3) AS expected_weight FROM (SELECT node_id, max(weight) AS weight, min(e) AS e FROM ed GROUP BY node_id) JOIN (SELECT node_id, sum(prob) AS mass FROM real GROUP BY node_id) USING (node_id)")
def absent_assigned_cost(spark, d):
    real = _absent(spark, d)
    return costs.best_assigned_cost(nodes.pack(real), {0: w.hash_centres(real, 5)}).select("set_id", F.round("cost", 3).alias("cost"), F.round("expected_weight", 3).alias("expected_weight"))


@query(f"{_CELLS}, {o.summary()}, {o.fixed_centres(n=D)}, {o.expected(n=D)}, {o.cost_of('full_', 'weight', '(SELECT node_id, weight, e FROM ed)')}, small AS (SELECT sum(new_weight * e) AS cost FROM (SELECT node_id, min(e) AS e FROM ed GROUP BY node_id) JOIN sw USING (node_id)) SELECT round(full_.cost, 3) AS cost_full, round(small.cost, 3) AS cost_summary, round(abs(small.cost - full_.cost) / full_.cost, 6) AS gap FROM full_, small".replace("SELECT sum(weight * e) AS cost FROM (SELECT node_id, min(e) AS e FROM (SELECT node_id, weight, e FROM ed) GROUP BY node_id)", "SELECT sum(weight * e) AS cost FROM (SELECT node_id, max(weight) AS weight, min(e) AS e FROM ed GROUP BY node_id)"))
def absent_summary_error(spark, d):
    packed, real = nodes.pack(_absent(spark, d)), _absent(spark, d)
    summary = cell_ops.summary_nodes(packed, _weights(spark, d, "weight"))
    found = costs.coreset_error_profile(packed, summary, {0: w.hash_centres(real, 5)})
    return found.select(F.round("cost_full", 3).alias("cost_full"), F.round("cost_summary", 3).alias("cost_summary"), F.round("relative_gap", 6).alias("gap"))


@query(f"{o.USERS} SELECT node_id, CAST(count(*) AS INTEGER) AS n, round(sum(prob), 6) AS mass FROM real GROUP BY node_id")
def stream_assembled_nodes(spark, d):
    """Nodes assembled from a stream of consecutive pairs, in slices that cut nodes, equal those of the whole table."""
    from .sources.tables import shared_folder
    from .streaming import ladder_stream as s

    root = shared_folder(spark)
    pairs = w.user_realisations(spark, d).withColumn("pairs", F.count("*").over(Window.partitionBy("node_id")).cast("int"))
    pairs.repartitionByRange(5, "loc_id").write.parquet(f"{root}/pairs")
    stream = spark.readStream.schema("node_id long, loc_id long, coords array<double>, prob double, weight double, pairs int").option("maxFilesPerTrigger", 2).parquet(f"{root}/pairs")
    s.stream_assembled(stream, f"{root}/nodes", f"{root}/checkpoint").awaitTermination()
    return spark.read.parquet(f"{root}/nodes/closed").select("node_id", F.size("support").alias("n"), F.round("mass", 6).alias("mass"))


# --- whole runs ----------------------------------------------------------------------------------------------------------------


@query(None)
def literal_end_to_end(spark, d):
    """The practical summariser with seeds by distance alone and without the guard on moved centres."""
    packed, _ = w.workload(spark, d, "tower")
    return _result_frame(spark, "literal", summarise.cluster_uncertain(packed, 5, replace(LITERAL, per_k=PER_K, capacity=256)))


def _experiment(name: str):
    def f(spark, d):
        packed, dim = w.workload(spark, d, name)
        return experiment.run(spark, packed, dim, name, ["summary", "full_solver"], [5, 10], [1, 2], _SMALL).drop("seconds")

    return f


for _name in ("cover", "census", "cross", "descriptors", "descriptors_pair", "orders_absent"):
    QUERIES[f"experiment_{_name}"] = _experiment(_name)


def _repeated(name: str, runs: int):
    def f(spark, d):
        packed, _ = w.workload(spark, d, name)
        return experiment.repeated(packed, 5, runs, replace(PRACTICAL, per_k=PER_K, capacity=256))

    return f


QUERIES["repetitions_tower"], QUERIES["repetitions_customers"] = _repeated("tower", 100), _repeated("customers", 100)


@query(None)
def repetition_statistics(spark, d):
    """Mean, median and variation coefficient of cost and gap over a hundred repetitions."""
    runs = kept(_repeated("tower", 100)(spark, d), "runs").withColumn("workload", F.lit("tower")).withColumn("method", F.lit("summary")).withColumn("k", F.lit(5))
    both = [experiment.run_statistics(runs, v).select(F.lit(v).alias("measure"), "runs", "mean", "median", "variation") for v in ("cost_full", "gap")]
    return both[0].unionByName(both[1])


@query(None)
def median_methods(spark, d):
    """Iterated against sampled medians on sparse, moderate and dense supports: mean spread of each, and their ratio."""
    out = None
    for name in ("orders", "parts", "suppliers"):
        packed, _ = w.workload(spark, d, name)
        one, two = (medians.node_medians(packed, replace(PRACTICAL, median=m)).agg(F.avg("spread").alias(m)) for m in ("iterative", "sampled"))
        row = one.crossJoin(two).select(F.lit(name).alias("workload"), "iterative", "sampled", (F.col("sampled") / F.col("iterative")).alias("ratio"))
        out = row if out is None else out.unionByName(row)
    return out


@query(f"{o.TOWER} SELECT count(DISTINCT node_id) AS n, count(*) AS pairs, count(*) * CAST({8 * (3 + 2)} AS BIGINT) + count(DISTINCT node_id) * CAST(24 AS BIGINT) AS bytes FROM real")
def memory_full(spark, d):
    return experiment.memory_of(w.workload(spark, d, "tower")[0])


@query(None)
def memory_summary(spark, d):
    """Bytes of the whole input, of its summary, and of the largest ladder that a task holds."""
    packed, _ = w.workload(spark, d, "tower")
    found = kept(summarise.summarise(packed, 5, _SMALL), "summary")
    return experiment.memory_table(packed, found, 5, _SMALL)
