"""Experiment runs and measures: cost, gap, quality, time, size, and their statistics over repetitions."""

from __future__ import annotations

from time import perf_counter

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import kernels
from ..model import PRACTICAL, SUMMARY, Profile
from ..operators.costs import best_assigned_cost
from ..operators.medians import packed_batches
from ..sources.tables import kept
from . import baselines
from .full_data import solve_full
from .summarise import FAN_IN, cluster_runs, cluster_uncertain, solve_local

MEASURES = "workload string, method string, k int, seed int, cost_full double, cost_summary double, gap double, summary_rows long, nodes long, seconds double, note string"


#: Bytes of an input (as `memory_of` counts them) that the full-data solver may hold in one task; larger ones are scanned, and their runs share scans.
TASK_BYTES = 64 << 20
#: Repetitions whose ladders a task holds.
SEEDS_A_SCAN = 10


def too_large(n: int, k: int, per_k: int) -> bool:
    """k is left out where the summary would be too large against the input."""
    return per_k * k >= n / 2


def run_method(nodes: DataFrame, d: int, method: str, k: int, seed: int, profile: Profile = PRACTICAL, restarts: int = 1) -> tuple:
    """(cost on the full set, cost on the summary, summary rows, seconds) of one run of a method."""
    t = perf_counter()
    if method == "summary":
        r = cluster_uncertain(nodes, k, profile, seed, restarts)
        return r.cost_full, r.cost_summary, r.summary.count(), perf_counter() - t
    if method == "uniform_sample":
        sample = baselines.uniform_sample(nodes, profile.per_k * k, seed)
        centres, cost, _ = solve_local(sample, k, seed, profile, restarts)
        rows = sample.count()
    elif method == "full_solver":
        centres, cost, _ = baselines.full_solver_local(nodes, k, seed, restarts)
        rows = nodes.count()
    elif method == "stream_kmeanspp":
        centres, rows = baselines.stream_kmeanspp(baselines.node_points(nodes), k, seed, profile.per_k * k)
        cost = float("nan")
    elif method == "feature_tree":
        centres, rows = baselines.feature_tree(baselines.node_points(nodes), k, seed, profile.per_k * k)
        cost = float("nan")
    elif method == "kmeanspp":
        centres, rows, cost = baselines.kmeans_points(kept(baselines.node_points(nodes), "points"), k, d, seed), nodes.count(), float("nan")
    elif method == "kmeans_library":  # parallel seeding of Spark's own KMeans, as a cross-check
        centres, rows, cost = baselines.kmeans_library(baselines.node_points(nodes), k, seed), nodes.count(), float("nan")
    elif method == "collapse_medians":
        from ..operators.medians import node_medians

        centres, rows, cost = baselines.collapse_medians(nodes, node_medians(nodes), k, d, seed), nodes.count(), float("nan")
    elif method == "collapse_means":
        centres, rows, cost = baselines.collapse_means(nodes, k, d, seed), nodes.count(), float("nan")
    else:
        raise ValueError(method)
    seconds = perf_counter() - t
    full = best_assigned_cost(nodes, {0: [list(map(float, c)) for c in centres]}).first()["cost"] if len(centres) else 0.0
    return full, cost, rows, seconds


def run(spark: SparkSession, nodes: DataFrame, d: int, name: str, methods: list[str], ks: list[int], seeds: list[int], profile: Profile = PRACTICAL, restarts: int = 1) -> DataFrame:
    """The measures table of all combinations; a k that is too large is reported as skipped."""
    n, pairs = nodes.agg(F.count("*"), F.sum(F.size("support.prob"))).first()
    rows, solved, large = [], {}, 24 * n + 8 * (d + 2) * (pairs or 0) > TASK_BYTES
    if "full_solver" in methods and n and large:  # seconds are those of all runs, in equal parts
        t = perf_counter()
        found = solve_full(nodes, [(k, seed) for k in ks for seed in seeds], restarts)
        solved = {("full_solver", *run): (cost, cost, n, (perf_counter() - t) / len(found)) for run, (_, cost, _) in found.items()}
    runs = [(k, seed) for k in ks for seed in seeds if not too_large(n, k, profile.per_k)]
    if "summary" in methods and runs and large:
        t = perf_counter()
        found = cluster_runs(nodes, runs, profile, restarts)
        solved |= {("summary", *run): (*x, (perf_counter() - t) / len(found)) for run, x in found.items()}
    for k in ks:
        for method in methods:
            if method in ("summary", "uniform_sample") and too_large(n, k, profile.per_k):
                rows.append((name, method, k, 0, None, None, None, None, n, None, "skipped: the summary would be too large"))
                continue
            for seed in seeds:
                full, small, size, seconds = solved.get((method, k, seed)) or run_method(nodes, d, method, k, seed, profile, restarts)
                known = small == small
                rows.append((name, method, k, seed, float(full), float(small) if known else None, abs(small - full) / full if known and full else None, int(size), n, seconds, ""))
    return spark.createDataFrame(rows, MEASURES)


def repeated(nodes: DataFrame, k: int, runs: int = 100, profile: Profile = PRACTICAL) -> DataFrame:
    """(seed, cost_full, cost_summary, gap, summary_rows) of `runs` repetitions of summary and solver.

    A task holds the ladders of SEEDS_A_SCAN repetitions over its partition, so that nodes are read once for so many and never
    shuffled; their summaries meet in a tree and are solved in a task for each repetition, and one scan gives all full costs.
    """
    import numpy as np
    import pyarrow as pa
    from pyspark import TaskContext

    columns = ["node_id", "weight", "mass", "support"]

    def ladders(seeds: range):
        def run(batches):
            shard = TaskContext.get().partitionId()
            held = {seed: kernels.Ladder(k, profile, seed * 7919 + shard) for seed in seeds}
            for block in packed_batches(batches):
                if profile.median == "iterative":  # the same for all of them
                    block = kernels.with_medians(block, profile, seeds[0])
                for ladder in held.values():
                    ladder.add(block)
            for seed, ladder in held.items():
                out = ladder.finish()
                if out is not None:
                    batch = kernels.to_arrow(kernels.with_medians(out, profile, seed))
                    yield batch.append_column("seed", pa.array([seed] * batch.num_rows, pa.int32())).append_column("shard", pa.array([shard] * batch.num_rows, pa.int64()))

        return run

    def meet(key: tuple, table: pa.Table) -> pa.Table:
        seed, group = (x.as_py() for x in key)
        block = kernels.from_arrow(table.drop_columns(["seed", "shard", "g"]))
        block = block.take(np.lexsort((block.copies, block.weight, block.level, block.node_id)))
        if len(block) > FAN_IN * profile.capacity_for(k):  # a solver's task takes less as it is
            block = kernels.reduce_block(block, k, profile, seed * 104_729 + group)
        out = kernels.to_arrow(block)
        return pa.Table.from_batches([out.append_column("seed", pa.array([seed] * out.num_rows, pa.int32())).append_column("shard", pa.array([group] * out.num_rows, pa.int64()))])

    def solved(key: tuple, table: pa.Table) -> pa.Table:
        seed = key[0].as_py()
        block = kernels.from_arrow(table.drop_columns(["seed", "shard"]))
        block = block.take(np.lexsort((block.weight, block.node_id)))
        centres, cost, _ = kernels.solve_assigned(block, k, seed, profile, 1)
        return pa.table({"seed": pa.array([seed], pa.int32()), "centres": pa.array([centres.tolist()], pa.list_(pa.list_(pa.float64()))), "cost_summary": [float(cost)], "summary_rows": pa.array([len(block)], pa.int64())})

    schema, found = SUMMARY + ", seed int, shard long", None
    for first in range(1, runs + 1, SEEDS_A_SCAN):
        own = nodes.select(columns).mapInArrow(ladders(range(first, min(first + SEEDS_A_SCAN, runs + 1))), schema)
        found = own if found is None else found.unionByName(own)
    found = kept(found, "ladders")
    shards, low = found.agg(F.max("shard") - F.min("shard") + 1, F.min("shard")).first()
    found = found.withColumn("shard", F.col("shard") - F.lit(low or 0))
    while shards:
        found = kept(found.withColumn("g", F.floor(F.col("shard") / FAN_IN).cast("long")).groupBy("seed", "g").applyInArrow(meet, schema), "merged")
        shards = -(-shards // FAN_IN) if shards > FAN_IN else 0
    rows = found.groupBy("seed").applyInArrow(solved, "seed int, centres array<array<double>>, cost_summary double, summary_rows long").collect()
    out = "seed int, cost_full double, cost_summary double, gap double, summary_rows long"
    full = {r["set_id"]: r["cost"] for r in best_assigned_cost(nodes, {r["seed"]: r["centres"] for r in rows}).collect()} if rows else {}
    gap = lambda small, whole: abs(small - whole) / whole if whole else 0.0
    return nodes.sparkSession.createDataFrame([(r["seed"], full[r["seed"]], r["cost_summary"], gap(r["cost_summary"], full[r["seed"]]), r["summary_rows"]) for r in rows], out)


def memory_of(nodes: DataFrame) -> DataFrame:
    """One row: nodes, (node, location) pairs and the bytes of both as numbers: coordinates, chance and id of a pair, three numbers a node."""
    d = F.size(F.get("support", F.lit(0))["coords"])
    pairs = F.size("support").cast("long")
    return nodes.agg(F.count("*").alias("n"), F.sum(pairs).alias("pairs"), (F.sum(pairs * (d + 2)) * 8 + F.count("*") * 24).alias("bytes"))


def memory_table(nodes: DataFrame, summary: DataFrame, k: int, profile: Profile = PRACTICAL) -> DataFrame:
    """Bytes of input and summary, and a bound of the ladder of one task: a full bucket and a summary at each level."""
    n = memory_of(nodes).select(F.lit("input").alias("what"), "n", "pairs", "bytes")
    u = memory_of(summary).select(F.lit("summary").alias("what"), "n", "pairs", "bytes")
    held = n.select(F.lit("ladder at most").alias("what"), F.least("n", F.lit(profile.capacity_for(k)) + F.lit(profile.per_k * k) * F.ceil(F.log2(F.greatest(F.col("n") / profile.capacity_for(k), F.lit(2.0))))).cast("long").alias("n"), "pairs", "bytes", F.col("n").alias("whole"))
    share = F.col("n") / F.col("whole")
    return n.unionByName(u).unionByName(held.select("what", "n", (F.col("pairs") * share).cast("long").alias("pairs"), (F.col("bytes") * share).cast("long").alias("bytes")))


def run_statistics(measures: DataFrame, value: str = "cost_full") -> DataFrame:
    """Mean, median and variation coefficient over the repetitions."""
    v = F.col(value)
    return measures.groupBy("workload", "method", "k").agg(F.count(v).alias("runs"), F.avg(v).alias("mean"), F.median(v).alias("median"), F.try_divide(F.stddev_samp(v), F.avg(v)).alias("variation"))


def quality_ratio(measures: DataFrame, baseline: str = "full_solver") -> DataFrame:
    """Each method's cost over the baseline's, seed by seed."""
    base = measures.where(F.col("method") == baseline).select("workload", "k", "seed", F.col("cost_full").alias("base"))
    return measures.where("note = ''").join(base, ["workload", "k", "seed"]).select("workload", "method", "k", "seed", (F.col("cost_full") / F.col("base")).alias("ratio"))


def gap_quality_link(measures: DataFrame) -> DataFrame:
    """Rank correlation over k of the median gap and the median quality ratio."""
    from pyspark.sql import Window

    ratio = quality_ratio(measures).where("method = 'summary'").groupBy("workload", "k").agg(F.median("ratio").alias("ratio"))
    gap = measures.where("method = 'summary' and note = ''").groupBy("workload", "k").agg(F.median("gap").alias("gap"))
    w = Window.partitionBy("workload")
    ranks = ratio.join(gap, ["workload", "k"]).select("workload", F.rank().over(w.orderBy("ratio")).alias("a"), F.rank().over(w.orderBy("gap")).alias("b"))
    return ranks.groupBy("workload").agg(F.corr("a", "b").alias("rank_correlation"))


def time_linearity(measures: DataFrame) -> DataFrame:
    """Slope and R2 of seconds against k."""
    return measures.where("note = ''").groupBy("workload", "method").agg(F.regr_slope("seconds", "k").alias("slope"), F.regr_r2("seconds", "k").alias("r2"))


def time_ratio(measures: DataFrame, ours: str = "summary") -> DataFrame:
    mean = measures.where("note = ''").groupBy("workload", "method", "k").agg(F.avg("seconds").alias("s"))
    own = mean.where(F.col("method") == ours).select("workload", "k", F.col("s").alias("own"))
    return mean.where(F.col("method") != ours).join(own, ["workload", "k"]).select("workload", "method", "k", (F.col("own") / F.col("s")).alias("time_ratio"))


def throughput(measures: DataFrame) -> DataFrame:
    return measures.where("note = ''").select("workload", "method", "k", "seed", (F.col("nodes") / F.col("seconds")).alias("nodes_per_second"))


def per_k_table(measures: DataFrame, value: str = "cost_full") -> DataFrame:
    """One row for each workload and k, one column a method."""
    return measures.groupBy("workload", "k").pivot("method").agg(F.median(value))


def summary_size(nodes: DataFrame, summary: DataFrame) -> DataFrame:
    n = nodes.agg(F.count("*").alias("n"), F.sum(F.size("support")).alias("pairs"))
    u = summary.agg(F.count("*").alias("rows"), F.sum("copies").alias("copies"), F.sum(F.size("support")).alias("summary_pairs"))
    return n.crossJoin(u).withColumn("nodes_per_row", F.col("n") / F.col("rows"))


def ladder_statistics(n: int, capacity: int) -> dict:
    """Depth, reductions, and the reductions a node undergoes at most."""
    full = n // capacity
    return {"full_buckets": full, "depth": full.bit_length(), "reductions": full - bin(full).count("1"), "most_per_node": max(0, full.bit_length() - 1), "occupancy": bin(full)[:1:-1]}


def tiny_optimum(nodes: DataFrame, k: int) -> float:
    """The exact optimum of at most 8 nodes."""
    import pyarrow as pa

    rows = nodes.select("node_id", "weight", "mass", "support").limit(9).toArrow()
    return kernels.exact_small(kernels.from_arrow(pa.table(rows)), k)[1]
