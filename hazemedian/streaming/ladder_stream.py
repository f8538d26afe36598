"""Streams of nodes: micro-batches into a stored ladder, keyed state with a ladder a shard, panes, sessions, late rows."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from .. import kernels
from ..model import PRACTICAL, SUMMARY, Profile
from ..operators.costs import assign_nodes
from ..operators.nodes import pack
from ..sources.tables import kept, read_snapshot, write_snapshot
from ..sources.workloads import event_coords
from ..plans.summarise import merge_tree, merged, partition_ladders, solve_local

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events_stream(spark: SparkSession, folder: str, files_per_batch: int = 1, watermark: str | None = "1 hour") -> DataFrame:
    """Slices of events in file order; the time column gets a zone, which watermarks need, and replayed rows leave."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp")).withColumn("coords", event_coords())
    return rows.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"]) if watermark else rows


def write_slices(events: DataFrame, folder: str, rows: int = 500, key: str = "event_id") -> None:
    """A replay folder: one file for each run of `rows` keys."""
    events.withColumn("_s", F.floor(F.col(key) / rows).cast("int")).repartitionByRange("_s").sortWithinPartitions("_s", key).write.mode("overwrite").partitionBy("_s").parquet(folder)


def user_panes(rows: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Closed nodes of a stream: a user's events in a tumbling (or sliding) pane, uniform over them, weight their number."""
    pane = F.window("ts", length, slide) if slide else F.window("ts", length)
    items = F.sort_array(F.collect_list(F.struct(F.col("event_id").alias("loc_id"), "coords")))
    grouped = rows.groupBy(pane.alias("pane"), "user_id").agg(items.alias("items"), F.count("*").alias("n"))
    support = F.transform("items", lambda x: F.struct(x["loc_id"].alias("loc_id"), x["coords"].alias("coords"), (F.lit(1.0) / F.col("n")).alias("prob")))
    name = F.col("user_id") * F.lit(100_000) + F.floor(F.unix_timestamp(F.col("pane.start")) / 86400)
    return grouped.select(name.alias("node_id"), F.col("n").cast("double").alias("weight"), F.lit(1.0).alias("mass"), support.alias("support"), F.col("pane.start").alias("pane"))


def user_sessions(rows: DataFrame, gap: str = "2 hours") -> DataFrame:
    """(user_id, start, n, mean value): bursts of a user's events."""
    grouped = rows.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n"), F.avg("value").alias("mean_value"))
    return grouped.select("user_id", F.col("s.start").alias("start"), "n", "mean_value")


def fold_batch(batch: DataFrame, batch_id: int, folder: str, k: int, profile: Profile = PRACTICAL, seed: int = 1) -> None:
    """Adds one micro-batch to the stored ladder.

    The newest version says which batch made it, so a batch that is replayed after a failure changes nothing.  Level
    j + 1 of the ladder holds the summary of 2^j batches; the carry is binary addition over batch numbers.
    """
    spark = batch.sparkSession
    done, stored = read_snapshot(spark, folder)
    if batch_id <= done or batch.isEmpty():
        return
    carry = merge_tree(kept(partition_ladders(batch, k, profile, seed + batch_id), "ladders"), k, profile, seed + batch_id).withColumn("rung", F.lit(1))
    if stored is not None:
        taken = {x["rung"] for x in stored.select("rung").distinct().collect()}
        rung = 1
        while rung in taken:
            both = carry.unionByName(stored.where(F.col("rung") == rung)).drop("rung").withColumn("shard", F.lit(0).cast("long"))
            stored = stored.where(F.col("rung") != rung)
            rung += 1
            carry = merged(both, k, profile, seed + 31 * batch_id + rung).drop("shard").withColumn("rung", F.lit(rung))
        carry = carry.withColumn("rung", F.lit(rung)).unionByName(stored)
    write_snapshot(carry, folder, batch_id)


def stream_foreach_batch(nodes: DataFrame, folder: str, checkpoint: str, k: int, profile: Profile = PRACTICAL, seed: int = 1, **trigger):
    """A query that folds every micro-batch of packed nodes into the ladder at `folder`."""
    return nodes.select("node_id", "weight", "mass", "support").writeStream.foreachBatch(lambda batch, batch_id: fold_batch(batch, batch_id, folder, k, profile, seed)).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def current_summary(spark: SparkSession, folder: str) -> DataFrame | None:
    """The union of the ladder's levels at this moment."""
    return read_snapshot(spark, folder)[1]


def current_centres(spark: SparkSession, folder: str, k: int, seed: int = 1):
    summary = current_summary(spark, folder)
    return None if summary is None else solve_local(summary.drop("rung"), k, seed)[0]


class LadderProcessor(StatefulProcessor):
    """A ladder for each shard in the state store; emits the shard's summary after every batch that changed it."""

    def __init__(self, k: int, profile: Profile, seed: int):
        self.k, self.profile, self.seed = k, profile, seed

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("ladder", "ladder binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = self.state.get() if self.state.exists() else None
        ladder = pickle.loads(held[0]) if held else kernels.Ladder(self.k, self.profile, self.seed * 7919 + int(key[0]))
        for part in rows:
            part = part.sort_values("node_id")
            nodes = [pickle.loads(x) for x in part["node"]]
            table = pa.table({"node_id": pa.array([x[0] for x in nodes], pa.int64()), "weight": pa.array([x[1] for x in nodes], pa.float64()), "mass": pa.array([x[2] for x in nodes], pa.float64()), "support": pa.array([x[3] for x in nodes], pa.list_(pa.struct([("loc_id", pa.int64()), ("coords", pa.list_(pa.float64())), ("prob", pa.float64())])))})
            if table.num_rows:
                ladder.add(kernels.from_arrow(table))
        self.state.update((pickle.dumps(ladder),))
        out = pickle.loads(pickle.dumps(ladder)).finish()
        if out is not None:
            yield pd.DataFrame({"shard": int(key[0]), "seen": ladder.seen, "rows": len(out), "weight": float(out.weight.sum()), "summary": [pickle.dumps(out)]})

    def close(self) -> None:
        pass


def stream_stateful(nodes: DataFrame, k: int, shards: int = 8, profile: Profile = PRACTICAL, seed: int = 1) -> DataFrame:
    """(shard, seen, rows, weight, summary): the newest summary of each shard; needs the RocksDB state store."""

    @F.pandas_udf("binary")
    def packed(node_id: pd.Series, weight: pd.Series, mass: pd.Series, support: pd.Series) -> pd.Series:
        plain = lambda s: [{"loc_id": int(x["loc_id"]), "coords": list(x["coords"]), "prob": float(x["prob"])} for x in s]
        return pd.Series([pickle.dumps((int(a), float(b), float(c), plain(s))) for a, b, c, s in zip(node_id, weight, mass, support, strict=True)])

    rows = nodes.select("node_id", packed("node_id", "weight", "mass", "support").alias("node")).withColumn("shard", F.pmod(F.xxhash64("node_id"), F.lit(shards)).cast("int"))
    return rows.groupBy("shard").transformWithStateInPandas(LadderProcessor(k, profile, seed), "shard int, seen long, rows long, weight double, summary binary", "Update", "None")


def score_stream(nodes: DataFrame, centres) -> DataFrame:
    """New nodes get their expected nearest centre as they arrive."""
    return assign_nodes(nodes, centres)


def windowed_summaries(nodes: DataFrame, k: int, profile: Profile = PRACTICAL, seed: int = 1, shards: int = 16) -> DataFrame:
    """One summary for each tumbling pane: a ladder for each of a pane's shards, then one reduction of their summaries."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        block = kernels.from_arrow(table.drop_columns(["pane", "shard"]))
        block = block.take(block.node_id.argsort(kind="stable"))
        if block.median is None:
            ladder = kernels.Ladder(k, profile, seed * 7919 + int(key[1].as_py()))
            ladder.add(block)
            block = ladder.finish()
        out = kernels.to_arrow(kernels.reduce_block(block, k, profile, seed))
        out = out.append_column("pane", pa.array([key[0].as_py()] * out.num_rows, pa.timestamp("us", "UTC")))
        return pa.Table.from_batches([out.append_column("shard", pa.array([0] * out.num_rows, pa.int32()))])

    schema = SUMMARY + ", pane timestamp, shard int"
    rows = nodes.select("node_id", "weight", "mass", "support", "pane", F.pmod(F.xxhash64("node_id"), F.lit(shards)).cast("int").alias("shard"))
    return rows.groupBy("pane", "shard").applyInArrow(run, schema).groupBy("pane", "shard").applyInArrow(run, schema).drop("shard")


def sliding_summary(panes: DataFrame, until, length: str = "7 days") -> DataFrame:
    """The summary of the window of `length` that ends at `until`: the union of its panes' summaries, whose errors don't add up."""
    return panes.where((F.col("pane") < F.lit(until)) & (F.col("pane") >= F.lit(until) - F.expr(f"INTERVAL {length}"))).drop("pane")


def assemble_batch(batch: DataFrame, batch_id: int, folder: str) -> None:
    """Pairs of a micro-batch, with those of still open nodes, become packed nodes as soon as all of a node's pairs are there.

    batch(node_id, loc_id, coords, prob, weight, pairs): `pairs` is the number of pairs of the node.  Complete nodes go to
    `folder`/closed, one part for each batch; the open pairs are the snapshot that the next batch starts from.  A replayed batch writes the
    same parts again, and one that the snapshot holds already changes nothing.
    """
    spark = batch.sparkSession
    done, held = read_snapshot(spark, f"{folder}/open")
    if batch_id <= done:
        return
    rows = batch.select("node_id", "loc_id", "coords", "prob", "weight", "pairs")
    rows = kept(rows if held is None else rows.unionByName(held), "pairs")
    full = rows.groupBy("node_id").agg(F.count("*").alias("n"), F.max("pairs").alias("p")).where("n >= p").select("node_id")
    pack(rows.join(full, "node_id", "left_semi")).write.mode("overwrite").parquet(f"{folder}/closed/batch={batch_id}")
    write_snapshot(rows.join(full, "node_id", "left_anti"), f"{folder}/open", batch_id)


def stream_assembled(pairs: DataFrame, folder: str, checkpoint: str, **trigger):
    """A query that assembles nodes from a stream of their pairs."""
    return pairs.writeStream.foreachBatch(lambda batch, batch_id: assemble_batch(batch, batch_id, folder)).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


