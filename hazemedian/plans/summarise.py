"""Summaries of packed nodes: a ladder in every partition, then a tree of merges; solving and evaluating on top.

Only summaries are shuffled.  A task holds one ladder, whose size depends on the capacity and the logarithm of the rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..model import PRACTICAL, SUMMARY, Profile
from ..operators.costs import best_assigned_cost
from ..operators.medians import packed_batches
from ..sources.tables import BATCH_BYTES, kept, small_batches

FAN_IN = 16


def partition_ladders(nodes: DataFrame, k: int, profile: Profile = PRACTICAL, seed: int = 1) -> DataFrame:
    """One summary of each partition, in one pass over the nodes; `shard` is the partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = TaskContext.get().partitionId()
        ladder = kernels.Ladder(k, profile, seed * 7919 + shard)
        for block in packed_batches(batches):
            ladder.add(block)
        out = ladder.finish()
        if out is not None:  # one budget leaves the task, so that a group of the tree holds at most fan_in budgets
            out = kernels.reduce_block(out, k, profile, seed * 15_485_863 + shard)
            for at in range(0, len(out), 4096):
                batch = kernels.to_arrow(out.take(np.arange(at, min(at + 4096, len(out)))))
                yield batch.append_column("shard", pa.array([shard] * batch.num_rows, pa.int64()))

    columns = [c for c in ("node_id", "weight", "mass", "support", "median", "spread", "level", "copies", "cell") if c in nodes.columns]
    return nodes.select(columns).mapInArrow(run, SUMMARY + ", shard long")


def shared_ladders(nodes: DataFrame, runs: list[tuple[int, int]], profile: Profile = PRACTICAL) -> DataFrame:
    """`partition_ladders` of several (k, seed) in one pass, which share the nodes' medians; `run` is the place in `runs`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = TaskContext.get().partitionId()
        ladders = [kernels.Ladder(k, profile, seed * 7919 + shard) for k, seed in runs]
        for block in packed_batches(batches):
            for own in dict.fromkeys(seed for _, seed in runs):
                known = kernels.with_medians(replace(block), profile, own * 7919 + shard)
                for ladder, (_, seed) in zip(ladders, runs, strict=True):
                    if seed == own:
                        ladder.add(known)
        for place, (ladder, (k, seed)) in enumerate(zip(ladders, runs, strict=True)):
            out = ladder.finish()
            if out is not None:
                out = kernels.reduce_block(out, k, profile, seed * 15_485_863 + shard)
                for at in range(0, len(out), 4096):
                    batch = kernels.to_arrow(out.take(np.arange(at, min(at + 4096, len(out)))))
                    yield batch.append_column("shard", pa.array([shard] * batch.num_rows, pa.int64())).append_column("run", pa.array([place] * batch.num_rows, pa.int32()))

    return nodes.select("node_id", "weight", "mass", "support").mapInArrow(run, SUMMARY + ", shard long, run int")


def cluster_runs(nodes: DataFrame, runs: list[tuple[int, int]], profile: Profile = PRACTICAL, restarts: int = 1) -> dict[tuple[int, int], tuple[float, float, int]]:
    """{(k, seed): (cost on the full set, cost on the summary, summary rows)} of `cluster_uncertain`: nodes are read twice for all runs."""
    with small_batches(nodes.sparkSession, BATCH_BYTES):
        found = kept(shared_ladders(nodes, runs, profile), "ladders")
    out = {}
    for place, (k, seed) in enumerate(runs):
        summary = merge_tree(found.where(F.col("run") == place).drop("run"), k, profile, seed)
        centres, cost, _ = solve_local(summary, k, seed, profile, restarts)
        out[k, seed] = centres, cost, summary.count()
    sets = {place: out[run][0].tolist() for place, run in enumerate(runs) if len(out[run][0])}
    with small_batches(nodes.sparkSession, BATCH_BYTES):
        full = {r["set_id"]: r["cost"] for r in best_assigned_cost(nodes, sets).collect()} if sets else {}
    return {run: (full.get(place, 0.0), out[run][1], out[run][2]) for place, run in enumerate(runs)}


def merged(summaries: DataFrame, k: int, profile: Profile, seed: int, fan_in: int = FAN_IN) -> DataFrame:
    """One tree level: summaries of `fan_in` neighbouring shards are joined and reduced."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        group = key[0].as_py()
        block = kernels.from_arrow(table.drop_columns(["shard", "g"]))
        block = block.take(np.lexsort((block.copies, block.weight, block.level, block.node_id)))  # one order for any arrival
        out = kernels.to_arrow(kernels.reduce_block(block, k, profile, seed * 104_729 + group))
        return pa.Table.from_batches([out.append_column("shard", pa.array([group] * out.num_rows, pa.int64()))])

    return summaries.withColumn("g", F.floor(F.col("shard") / fan_in).cast("long")).groupBy("g").applyInArrow(run, SUMMARY + ", shard long")


def summarise(nodes: DataFrame, k: int, profile: Profile = PRACTICAL, seed: int = 1, fan_in: int = FAN_IN) -> DataFrame:
    """The (k, eps)-style summary of all nodes: weighted nodes with their medians, in the schema of nodes with lineage.

    With no more nodes than the budget the summary is the input itself and its error 0.
    """
    return merge_tree(kept(partition_ladders(nodes, k, profile, seed), "ladders"), k, profile, seed, fan_in)


def merge_tree(found: DataFrame, k: int, profile: Profile, seed: int, fan_in: int = FAN_IN) -> DataFrame:
    """Summaries with their `shard`, merged level by level until one is left."""
    shards = (found.agg(F.max("shard")).first()[0] or 0) + 1
    turn = 1
    while True:
        found = kept(merged(found, k, profile, seed + turn, fan_in), "merged")
        shards, turn = -(-shards // fan_in), turn + 1
        if shards <= 1:
            return found.drop("shard")


def summarise_at_once(nodes: DataFrame, k: int, profile: Profile = PRACTICAL, seed: int = 1) -> DataFrame:
    """One reduction of everything, no ladder: shows what the ladder's composed error costs.  For inputs that fit a task."""

    def run(_key: tuple, table: pa.Table) -> pa.Table:
        block = kernels.from_arrow(table.drop_columns(["g"]))
        return pa.Table.from_batches([kernels.to_arrow(kernels.reduce_block(block.take(np.argsort(block.node_id)), k, profile, seed))])

    return nodes.select("node_id", "weight", "mass", "support").withColumn("g", F.lit(0)).groupBy("g").applyInArrow(run, SUMMARY)


def flat_reduce(nodes: DataFrame, k: int, profile: Profile = PRACTICAL, seed: int = 1) -> DataFrame:
    """The strawman of a stream: one summary that is reduced again with every chunk, so that errors pile up with the chunks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, turn, size = None, 0, profile.capacity_for(k)
        for block in packed_batches(batches, size):
            block = kernels.with_medians(block, profile, seed)
            turn += 1
            now = kernels.reduce_block(block if now is None else kernels.Block.join([now, block]), k, profile, seed + turn)
        if now is not None:
            yield kernels.to_arrow(now)

    return nodes.select("node_id", "weight", "mass", "support").repartition(1).sortWithinPartitions("node_id").mapInArrow(run, SUMMARY)


def merge_summaries(*summaries: DataFrame) -> DataFrame:
    """The union of summaries of disjoint node sets is a summary of their union, with the larger of the errors."""
    out = summaries[0]
    for x in summaries[1:]:
        out = out.unionByName(x)
    return out


def composed_error(errors: list[float]) -> float:
    """The error of summaries of summaries: product of (1 + eps) less 1."""
    return float(np.prod([1 + e for e in errors]) - 1)


def composed_errors(errors: DataFrame, by: str, error: Column) -> DataFrame:
    """(`by`, error): the composed error of each group's errors."""
    return errors.groupBy(by).agg((F.exp(F.sum(F.ln(1 + error))) - 1).alias("error"))


def level_epsilon(eps: float, depth: int) -> float:
    """The error that each of `depth` reductions may make for `eps` in all."""
    return (1 + eps) ** (1 / max(depth, 1)) - 1


def level_epsilons(nodes: DataFrame, by: str, eps: float, log_capacity: int) -> DataFrame:
    """(`by`, depth, eps): the levels that a ladder of 2^log_capacity nodes gets over each group's rows, at least one, and each level's error for `eps` in all."""
    full = F.shiftright(F.count("*"), log_capacity)
    depths = nodes.groupBy(by).agg(F.length(F.bin(full)).alias("depth"))
    return depths.select(by, "depth", (F.pow(F.lit(1 + eps), 1 / F.col("depth")) - 1).alias("eps"))


def ladder_levels(n: int, capacity: int) -> list[tuple[int, int]]:
    """(level, nodes it stands for) after n nodes: the binary digits of n div capacity."""
    full = n // capacity
    return [(0, n % capacity)] + [(j + 1, capacity << j) for j in range(full.bit_length()) if full >> j & 1]


@dataclass
class Result:
    centres: np.ndarray
    summary: DataFrame
    cost_full: float
    cost_summary: float
    rounds: int
    seconds: dict[str, float]

    @property
    def gap(self) -> float:
        """Difference of the costs on summary and full set, over the latter."""
        return abs(self.cost_summary - self.cost_full) / self.cost_full if self.cost_full else 0.0


def solve_local(nodes: DataFrame, k: int, seed: int = 1, profile: Profile = PRACTICAL, restarts: int = 1, solver=None) -> tuple[np.ndarray, float, int]:
    """The whole-node solver (or another callable) on a summary: one bounded task, k centres come back."""

    def run(_key: tuple, table: pa.Table) -> pa.Table:
        block = kernels.from_arrow(table.drop_columns(["g"]))
        block = block.take(np.lexsort((block.weight, block.node_id)))
        c, cost, rounds = (solver or kernels.solve_assigned)(block, k, seed, profile, restarts)
        return pa.table({"centres": pa.array([c.ravel()], pa.list_(pa.float64())), "k": pa.array([len(c)], pa.int32()), "cost": [float(cost)], "rounds": pa.array([rounds], pa.int32())})

    columns = [c for c in ("node_id", "weight", "mass", "support", "median", "spread", "level", "copies", "cell") if c in nodes.columns]
    columns = columns if "cell" in columns else columns[:4]
    row = nodes.select(columns).withColumn("g", F.lit(0)).groupBy("g").applyInArrow(run, "centres array<double>, k int, cost double, rounds int").first()
    if row is None:  # no nodes: no centres, at no cost
        return np.zeros((0, 0)), 0.0, 0
    return np.array(row["centres"]).reshape(row["k"], -1), row["cost"], row["rounds"]


def cluster_uncertain(nodes: DataFrame, k: int, profile: Profile = PRACTICAL, seed: int = 1, restarts: int = 1, ladder: bool = True, solver=None) -> Result:
    """End to end: summary in one pass, solver on the summary, one more pass to evaluate.

    solver(block, k, seed, profile, restarts) -> (centres, cost, rounds) takes the place of the whole-node solver.  Without
    nodes there are no centres and all costs are 0.
    """
    from time import perf_counter

    t0 = perf_counter()
    summary = summarise(nodes, k, profile, seed) if ladder else kept(summarise_at_once(nodes, k, profile, seed))
    t1 = perf_counter()
    centres, cost, rounds = solve_local(summary, k, seed, profile, restarts, solver)
    t2 = perf_counter()
    full = best_assigned_cost(nodes, {0: centres.tolist()}).first()["cost"] if len(centres) else 0.0
    t3 = perf_counter()
    return Result(centres, summary, full, cost, rounds, {"summarise": t1 - t0, "solve": t2 - t1, "evaluate": t3 - t2})


class UncertainKMedian:
    """fit(nodes) -> model with centres; model.transform(nodes) -> nodes with centre_id and expected_distance."""

    def __init__(self, k: int, profile: Profile = PRACTICAL, seed: int = 1, restarts: int = 1):
        self.k, self.profile, self.seed, self.restarts = k, profile, seed, restarts

    def fit(self, nodes: DataFrame) -> UncertainKMedianModel:
        return UncertainKMedianModel(cluster_uncertain(nodes, self.k, self.profile, self.seed, self.restarts))


class UncertainKMedianModel:
    def __init__(self, result: Result):
        self.result = result

    def transform(self, nodes: DataFrame) -> DataFrame:
        from ..operators.costs import assign_nodes

        return assign_nodes(nodes, self.result.centres.tolist())
