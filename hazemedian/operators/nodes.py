"""Building, packing, checking and describing nodes."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import kernels
from ..functions.expressions import column
from ..model import MASS_SLACK
from ..sources.tables import kept

PARTITION_ROWS = 1_000_000
#: Rows of a task that packs them with coordinates of any number.
PACKED_ROWS = 100_000
#: Different points of one side of a join's task; larger blocks are dealt over several.
TASK_POINTS = 16_384
#: Pairs of points that a task of a join looks at: few enough for some parallel tasks on a small input, and the most on a large one.
FEW_PAIRS, MOST_PAIRS = 2**22, 2**30


def row_positions(df: DataFrame, order_by: Sequence[str], partitions: int | None = None) -> DataFrame:
    """`df` with `pos` from 0 in the order of a unique key, without a one-task sort.

    The input is written first, so that a join behind it runs once.  Rows are sorted by ranges; a range's rows are numbered where they are, and the counts of the ranges before are added.  The
    sorted ranges are written once, because a second evaluation could cut them elsewhere.
    """
    df = kept(df, "points")
    partitions = partitions or max(1, -(-df.count() // PARTITION_ROWS))
    ranged = df.repartitionByRange(partitions, *order_by).sortWithinPartitions(*order_by)
    ranged = kept(ranged.withColumn("_m", F.monotonically_increasing_id()).withColumn("_p", F.shiftright("_m", 33)).withColumn("_m", F.col("_m") - F.shiftleft("_p", 33)), "ranged")
    counts = ranged.groupBy("_p").agg(F.count("*").alias("_n"))
    before = counts.withColumn("_before", F.sum("_n").over(Window.orderBy("_p")) - F.col("_n")).drop("_n")
    return ranged.join(F.broadcast(before), "_p").withColumn("pos", F.col("_m") + F.col("_before")).drop("_p", "_m", "_before")


def chunk_realisations(points: DataFrame, order_by: Sequence[str], coords: Column, size: int = 10, drop_tail: bool = True, loc_id: Column | None = None) -> DataFrame:
    """Long rows of chunk nodes: each run of `size` points in order becomes a node of equal chances.

    An incomplete tail is dropped, or makes a smaller node with chances over its own size.  loc_id is the position unless given.
    """
    placed, prob = _chunked(points, order_by, size, drop_tail)
    return placed.select("node_id", (F.col("pos") if loc_id is None else loc_id).cast("long").alias("loc_id"), coords.alias("coords"), prob.alias("prob"), F.lit(1.0).alias("weight"))


def _chunked(points: DataFrame, order_by: Sequence[str], size: int, drop_tail: bool) -> tuple[DataFrame, Column]:
    """The points with `pos` and `node_id`, and each one's chance."""
    placed = row_positions(points, order_by)
    total = placed.count()
    full = total // size * size
    if drop_tail:
        placed = placed.where(F.col("pos") < full)
    share = F.when(F.col("pos") < full, F.lit(1.0 / size)).otherwise(F.lit(1.0 / max(total - full, 1)))
    return placed.withColumn("node_id", F.floor(F.col("pos") / size).cast("long")), share


def keyed_realisations(df: DataFrame, key: str, coords: Column, loc_id: Column | str, share_of: Column | str | None = None, presence: Column | str | None = None, weight: Column | None = None) -> DataFrame:
    """Long rows of the nodes named by `key`: uniform over the key's rows, or in proportion to `share_of`, times `presence` (at most 1)."""
    own = Window.partitionBy("node_id")
    share = column(share_of) if share_of is not None else F.lit(1.0)
    rows = df.select(F.col(key).cast("long").alias("node_id"), column(loc_id).cast("long").alias("loc_id"), coords.alias("coords"), share.cast("double").alias("_share"), (column(presence) if presence is not None else F.lit(1.0)).alias("_there"), (weight if weight is not None else F.lit(1.0)).cast("double").alias("weight"))
    prob = F.col("_share") / F.sum("_share").over(own) * F.col("_there")
    return rows.withColumn("prob", prob).select("node_id", "loc_id", "coords", "prob", "weight")


def pack(realisations: DataFrame) -> DataFrame:
    """One row a node; impossible locations (probability 0) leave."""
    item = F.struct("loc_id", "coords", "prob")
    found = realisations.where("prob > 0").groupBy("node_id").agg(F.max("weight").alias("weight"), F.sum("prob").alias("mass"), F.sort_array(F.collect_list(item)).alias("support"))
    return found.select("node_id", "weight", "mass", "support")


def unpack(nodes: DataFrame) -> DataFrame:
    return nodes.select("node_id", "weight", F.inline("support")).select("node_id", "loc_id", "coords", "prob", "weight")


def chunk_nodes(points: DataFrame, order_by: Sequence[str], coords: Column, size: int = 10, drop_tail: bool = True) -> DataFrame:
    """Packed chunk nodes; coordinates are made where the nodes are packed, so that only the columns that they come from are shuffled and kept."""
    placed, prob = _chunked(points, order_by, size, drop_tail)
    parts = max(points.sparkSession.sparkContext.defaultParallelism, -(-placed.count() // PACKED_ROWS))
    return pack(placed.repartition(parts, "node_id").select("node_id", F.col("pos").alias("loc_id"), coords.alias("coords"), prob.alias("prob"), F.lit(1.0).alias("weight")))


def keyed_nodes(df: DataFrame, key: str, coords: Column, loc_id: Column | str, **options) -> DataFrame:
    return pack(keyed_realisations(df, key, coords, loc_id, **options))


def certain_nodes(points: DataFrame, key: str = "loc_id", weight: Column | None = None) -> DataFrame:
    """Deterministic points as nodes of one location."""
    item = F.struct(F.col(key).cast("long").alias("loc_id"), "coords", F.lit(1.0).alias("prob"))
    return points.select(F.col(key).cast("long").alias("node_id"), (weight if weight is not None else F.lit(1.0)).cast("double").alias("weight"), F.lit(1.0).alias("mass"), F.array(item).alias("support"))


def with_weight(nodes: DataFrame, weights: DataFrame) -> DataFrame:
    """Nodes with the weights of `weights(node_id, weight)`, 1 where none is given."""
    return nodes.drop("weight").join(weights, "node_id", "left").withColumn("weight", F.coalesce("weight", F.lit(1.0))).select(nodes.columns)


def merge_locations(realisations: DataFrame) -> DataFrame:
    """Equal locations of a node become one; their chances add up."""
    return realisations.groupBy("node_id", "coords").agg(F.min("loc_id").alias("loc_id"), F.sum("prob").alias("prob"), F.max("weight").alias("weight")).select("node_id", "loc_id", "coords", "prob", "weight")


def location_universe(realisations: DataFrame) -> DataFrame:
    """The different locations, with the number of nodes that can be there and their total realisation weight."""
    return realisations.where("prob > 0").groupBy("coords").agg(F.min("loc_id").alias("loc_id"), F.count_distinct("node_id").alias("n_nodes"), F.sum(F.col("weight") * F.col("prob")).alias("score"))


def match_nodes(left: DataFrame, right: DataFrame, block: str, score: Column) -> DataFrame:
    """Long rows of an uncertain join: a left row is realised at each right row of its block in proportion to a score.

    left(node_id, block...), right(loc_id, coords, block...); `score` is over both sides' columns.  The rows are all pairs, which grow with the square
    of a block, and pass a shuffle; `match_links` sums them up where they are made.
    """
    pairs = left.join(right, block).withColumn("_score", score).where("_score > 0")
    return pairs.withColumn("prob", F.col("_score") / F.sum("_score").over(Window.partitionBy("node_id"))).select("node_id", "loc_id", "coords", "prob", F.lit(1.0).alias("weight"))


def match_links(points: DataFrame, block: str, slope: float) -> DataFrame:
    """(node_id, class_id, score, n) of the uncertain join of points(node_id, coords, block) with themselves: a row for each node of `match_nodes` with the score
    1 - slope * (L1 distance), the sum of its scores and the number of its locations.  A location's chance is its score over that sum.

    Equal points of a block are one class, named by its least node_id and looked at once.  Classes, not pairs, are shuffled: a block of more than TASK_POINTS classes is dealt by
    hash into parts, and each two parts meet in one task, which sums all their pairs.
    """
    points = kept(points.where(f"{block} IS NOT NULL AND coords IS NOT NULL").select("node_id", block, "coords"), "points")
    classes = kept(points.groupBy(block, "coords").agg(F.count("*").alias("copies"), F.min("node_id").alias("class_id")), "classes")
    sizes = classes.groupBy(block).agg(F.count("*").alias("_n"))
    pairs = sizes.agg(F.sum(F.col("_n").cast("double") * F.col("_n"))).first()[0] or 0.0
    width = int(max(1, min(pairs // FEW_PAIRS, 4 * points.sparkSession.sparkContext.defaultParallelism), pairs // MOST_PAIRS))
    dealt = classes.join(sizes.select(block, F.ceil(F.col("_n") / TASK_POINTS).alias("_parts")), block).withColumn("_own", F.pmod(F.xxhash64("coords"), F.col("_parts")))
    met = dealt.withColumn("_other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_parts") - 1)))
    met = met.select(block, "coords", "copies", "class_id", "_own", F.least("_own", "_other").alias("_lo"), F.greatest("_own", "_other").alias("_hi"))

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        own, lo = (table[c].to_numpy() for c in ("_own", "_lo"))
        x, copies = np.stack(table["coords"].to_numpy()), table["copies"].to_numpy()
        first, found = own == lo, np.empty((len(x), 2))
        if first.all() or not first.any():
            found[:] = kernels.match_totals(x, copies, x, copies, slope)[0] if lo[0] == table["_hi"][0].as_py() else 0.0
        else:
            found[first], found[~first] = kernels.match_totals(x[first], copies[first], x[~first], copies[~first], slope)
        return table.select([block, "coords", "class_id"]).append_column("score", pa.array(found[:, 0])).append_column("n", pa.array(found[:, 1].astype(np.int64)))

    schema = T.StructType([*(classes.schema[c] for c in (block, "coords", "class_id")), T.StructField("score", T.DoubleType()), T.StructField("n", T.LongType())])
    key = [block, "_lo", "_hi"]
    sums = [F.min("class_id").alias("class_id"), F.sum("score").alias("score"), F.sum("n").alias("n")]
    totals = kept(met.repartition(width, *key).groupBy(*key).applyInArrow(run, schema).groupBy(block, "coords").agg(*sums), "totals")
    return points.join(totals, [block, "coords"]).groupBy("node_id").agg(*sums)


def validate_nodes(realisations: DataFrame) -> DataFrame:
    """(node_id, problem) of every node that breaks the model; empty if all is well."""
    bad_number = lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
    d = F.size("coords")
    found = realisations.groupBy("node_id").agg(
        F.min("prob").alias("lo"), F.sum("prob").alias("mass"), F.min("weight").alias("w"), F.min(d).alias("d0"), F.max(d).alias("d1"),
        F.max(F.exists("coords", lambda x: bad_number(x)).cast("int")).alias("odd"), F.max(F.col("prob").isNull().cast("int")).alias("no_prob"),
    )
    rules = [("no probability", "no_prob = 1"), ("probability not positive", "lo <= 0"), ("mass above 1", f"mass > {1 + MASS_SLACK}"), ("negative weight", "w < 0"), ("mixed dimensions", "d0 <> d1"), ("coordinate not finite", "odd = 1")]
    hits = F.array_compact(F.array(*(F.when(F.expr(rule), F.lit(name)) for name, rule in rules)))
    return found.select("node_id", F.explode(hits).alias("problem"))


def instance_stats(realisations: DataFrame) -> DataFrame:
    """One row: n, m, d, p_min, w_min, expected_weight, max_support, mean_support."""
    real = realisations.where("prob > 0")
    per = real.groupBy("node_id").agg(F.max("weight").alias("w"), F.sum("prob").alias("mass"), F.count("*").alias("z"), F.min("prob").alias("p"), F.max(F.size("coords")).alias("d"))
    one = per.agg(F.count("*").alias("n"), F.max("d").alias("d"), F.min("p").alias("p_min"), F.least(F.min("w"), F.lit(1.0)).alias("w_min"), F.sum(F.col("w") * F.col("mass")).alias("expected_weight"), F.max("z").alias("max_support"), F.avg("z").alias("mean_support"))
    return one.crossJoin(real.agg(F.count_distinct("coords").alias("m")))


def with_copies(realisations: DataFrame, eps: float) -> DataFrame:
    """Each pair with its multiplicity in the unweighted multiset; never expanded."""
    low = realisations.where("prob > 0").agg(F.min("prob").alias("p_min"), F.least(F.min("weight"), F.lit(1.0)).alias("w_min"))
    ratio = F.col("weight") * F.col("prob") / (F.col("w_min") * F.col("p_min") * F.lit(eps))
    return realisations.crossJoin(F.broadcast(low)).withColumn("copies", F.floor(F.round(ratio, 9))).drop("p_min", "w_min")
