"""The experiment inputs on the given tables: feature points with fixed scales, and the nodes made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.expressions import portable_uniform
from ..operators.nodes import PARTITION_ROWS, chunk_nodes, chunk_realisations, keyed_realisations, match_nodes, pack
from .tables import kept, table

LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity"]
#: Categories of the tables, in the tables' own spelling.
FLAGS, STATES = ["A", "N", "R"], ["F", "O"]
ORDER_STATES = ["F", "O", "P"]
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]


def one_hot(c: Column | str, values: list) -> list[Column]:
    c = F.col(c) if isinstance(c, str) else c
    return [F.coalesce((c == F.lit(v)).cast("double"), F.lit(0.0)) for v in values]


def event_coords() -> Column:
    k = F.regexp_extract("props", r'"k": *(-?\d+)', 1).cast("double")
    return F.array(F.hour("ts") / F.lit(23.0), F.col("value") / F.lit(490.02), k / F.lit(99.0))


def line_coords() -> Column:
    return F.array(F.col("l_quantity") / F.lit(50.0), F.col("l_extendedprice") / F.lit(104997.88), (F.col("l_discount") + F.lit(0.0)) * F.lit(10.0), (F.col("l_tax") + F.lit(0.0)) * F.lit(12.5))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events", "event_id", "ts", "user_id", "value", "props").withColumn("coords", event_coords())


def tower_realisations(spark: SparkSession, sf_dir: str, drop_tail: bool = True) -> DataFrame:
    """Ten consecutive events make a node, d = 3."""
    return chunk_realisations(events(spark, sf_dir).select("event_id", "coords"), ["event_id"], F.col("coords"), drop_tail=drop_tail, loc_id=F.col("event_id"))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem", *LINE_KEY, "l_discount", "l_tax", "l_returnflag", "l_linestatus")


def line_realisations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten consecutive line items make a node, d = 4."""
    return chunk_realisations(lines(spark, sf_dir).select(*LINE_KEY, line_coords().alias("coords")), LINE_KEY, F.col("coords"))


def _year_day(c: str) -> Column:
    return F.dayofyear(c) / F.lit(366.0)


def cover_points(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, Column]:
    """Line items with order and part, and their coordinates: 11 scaled numbers and 44 indicators, d = 55."""
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
    part = table(spark, sf_dir, "part", "p_partkey", "p_brand", "p_type", "p_size", "p_retailprice")
    rows = lines(spark, sf_dir).join(orders, F.col("l_orderkey") == F.col("o_orderkey"), "left").join(part, F.col("l_partkey") == F.col("p_partkey"), "left")
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    numbers = [F.col("l_quantity") / 50, F.col("l_extendedprice") / 104997.88, (F.col("l_discount") + 0.0) * 10, (F.col("l_tax") + 0.0) * 12.5, F.col("l_linenumber") / 7, _year_day("l_shipdate"), F.col("o_totalprice") / 500000, F.col("p_size") / 50, F.col("p_retailprice") / 2000, _year_day("o_orderdate"), F.datediff("l_shipdate", "o_orderdate") / 365]
    brands = [f"Brand#{a}{b}" for a in range(1, 6) for b in range(1, 6)]
    kinds = [F.when(F.pmod(F.crc32(F.split("p_type", " ")[0].cast("binary")), F.lit(6)) == v, 1.0).otherwise(0.0) for v in range(6)]
    coords = [*(zero(x) for x in numbers), *one_hot("l_returnflag", FLAGS), *one_hot("l_linestatus", STATES), *one_hot("o_orderpriority", PRIORITIES), *one_hot("o_orderstatus", ORDER_STATES), *one_hot("p_brand", brands), *kinds]
    used = ["l_discount", "l_tax", "l_returnflag", "l_linestatus", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority", "p_brand", "p_type", "p_size", "p_retailprice"]
    return rows.select(*LINE_KEY, *used), F.array(*coords)


def census_points(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, Column]:
    """Line items with order, customer, nation and region, and their coordinates: 67 indicators and the discount, d = 68; many equal locations."""
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_orderdate", "o_orderpriority")
    customer = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_mktsegment")
    nation = table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    who = orders.join(customer, F.col("o_custkey") == F.col("c_custkey"), "left").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"), "left")
    rows = lines(spark, sf_dir).join(who, F.col("l_orderkey") == F.col("o_orderkey"), "left")
    segments = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    coords = [*one_hot("l_returnflag", FLAGS), *one_hot("l_linestatus", STATES), *one_hot("l_linenumber", list(range(1, 8))), *one_hot("o_orderpriority", PRIORITIES), *one_hot("c_mktsegment", segments), *one_hot("c_nationkey", list(range(25))), *one_hot("n_regionkey", list(range(5))), *one_hot("o_orderstatus", ORDER_STATES), *one_hot(F.month("o_orderdate"), list(range(1, 13))), (F.col("l_discount") + 0.0) * 10]
    used = ["l_discount", "l_returnflag", "l_linestatus", "o_orderstatus", "o_orderdate", "o_orderpriority", "c_mktsegment", "c_nationkey", "n_regionkey"]
    return rows.select(*LINE_KEY, *used), F.array(*coords)


def big_cross_points(spark: SparkSession, sf_dir: str, keep_one_in: int = 10) -> tuple[DataFrame, Column]:
    """A hash-chosen part of part x supplier, and its coordinates, d = 57.  The product is this workload's definition; each part row meets only the
    suppliers that its hash keeps, one in `keep_one_in`.  A task makes about PARTITION_ROWS pairs: suppliers are sent to all
    tasks, as they are few against the pairs."""
    part = table(spark, sf_dir, "part", "p_partkey", "p_size", "p_brand")
    supplier = table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal", "s_nationkey").join(F.broadcast(table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")), F.col("s_nationkey") == F.col("n_nationkey"))
    parts = max(spark.sparkContext.defaultParallelism, -(-part.count() * supplier.count() // (keep_one_in * PARTITION_ROWS)))
    supplier = supplier.withColumn("_h", F.pmod(F.xxhash64("s_suppkey"), F.lit(keep_one_in)))
    pairs = part.repartition(parts, "p_partkey").withColumn("_h", F.pmod(F.xxhash64("p_partkey"), F.lit(keep_one_in))).join(F.broadcast(supplier), "_h")
    brands = [f"Brand#{a}{b}" for a in range(1, 6) for b in range(1, 6)]
    coords = F.array(F.col("p_size") / 50, *one_hot("p_brand", brands), F.col("s_acctbal") / 10000, *one_hot("s_nationkey", list(range(25))), *one_hot("n_regionkey", list(range(5))))
    return pairs.select("p_partkey", "s_suppkey", "p_size", "p_brand", "s_acctbal", "s_nationkey", "n_regionkey"), coords


def descriptor_points(spark: SparkSession, sf_dir: str, pair: bool = False) -> DataFrame:
    """Embeddings as doubles, d = 64; with `pair` two neighbours make one point, d = 128."""
    rows = table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("coords"))
    if not pair:
        return rows
    odd = rows.where("vec_id % 2 = 1").select((F.col("vec_id") - 1).alias("vec_id"), F.col("coords").alias("more"))
    return rows.join(odd, "vec_id").select("vec_id", F.concat("coords", "more").alias("coords"))


def order_realisations(spark: SparkSession, sf_dir: str, absent: bool = False) -> DataFrame:
    """A node for each order: lines by their share of the quantity; with `absent` realised with chance 1 - discount and weighted by price."""
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").withColumnRenamed("o_orderkey", "l_orderkey")
    rows = lines(spark, sf_dir).withColumn("loc", F.col("l_orderkey") * 100_000_000 + F.col("l_linenumber") * 10_000_000 + F.col("l_partkey"))
    rows = rows.withColumn("there", F.lit(1.0) - (F.col("l_discount") + 0.0))
    if not absent:
        return keyed_realisations(rows, "l_orderkey", line_coords(), "loc", share_of="l_quantity")
    return keyed_realisations(rows.join(orders, "l_orderkey"), "l_orderkey", line_coords(), "loc", share_of="l_quantity", presence="there", weight=F.col("o_totalprice") / 1e5)


def keyed_lines(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """A node for each part (moderate supports) or supplier (dense ones)."""
    rows = lines(spark, sf_dir).withColumn("loc", F.xxhash64(*LINE_KEY))
    return keyed_realisations(rows, key, line_coords(), "loc")


def user_realisations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A node for each user, uniform over the user's events."""
    return keyed_realisations(events(spark, sf_dir), "user_id", F.col("coords"), "event_id")


def customer_points(spark: SparkSession, sf_dir: str, shift: bool = True, far: bool = True) -> DataFrame:
    """Orders as points of their customer's node; planted nation groups and a few far customers."""
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderdate")
    customer = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    rows = orders.join(customer, F.col("o_custkey") == F.col("c_custkey"))
    move = F.when(F.pmod("o_custkey", F.lit(200)) == 7, 200.0).otherwise(0.0) if far else F.lit(0.0)
    step = 10.0 if shift else 0.0
    coords = F.array(F.col("o_totalprice") / F.lit(500000.0) + F.pmod("c_nationkey", F.lit(5)) * F.lit(step) + move, F.dayofyear("o_orderdate") / F.lit(366.0) + F.floor(F.col("c_nationkey") / 5) * F.lit(step) + move)
    return rows.select("o_custkey", "o_orderkey", coords.alias("coords"))


def customer_realisations(spark: SparkSession, sf_dir: str, shift: bool = True, far: bool = True) -> DataFrame:
    return keyed_realisations(customer_points(spark, sf_dir, shift, far), "o_custkey", F.col("coords"), "o_orderkey")


#: A match's score falls from 1 to 0 while the distance of the counts goes from 0 to one over this.
MATCH_SLOPE = 4


def match_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, coords, block): shares of a document's words in eight hash classes, d = 8; the block is language and length class."""
    words = F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+")
    hashed = F.transform(words, lambda w: F.pmod(F.crc32(w.cast("binary")), F.lit(8)))
    shares = lambda h: F.array(*((F.size(h) - F.size(F.array_remove(h, F.lit(k).cast("long")))) / F.greatest(F.size(h), F.lit(1)) for k in range(8)))
    # a function of the one element of an array, so that a text's words are hashed once
    coords = F.get(F.transform(F.array(hashed), shares), F.lit(0))
    return table(spark, sf_dir, "documents", "doc_id", "text", "lang", "n_chars").select("doc_id", coords.alias("coords"), F.concat_ws("/", "lang", F.floor(F.col("n_chars") / 64)).alias("block"))


def match_realisations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Uncertain entity join: a document may be each document of its language and length class whose counts are near its own."""
    docs = match_points(spark, sf_dir)
    left = docs.select(F.col("doc_id").alias("node_id"), F.col("coords").alias("own"), "block")
    gap = F.aggregate(F.zip_with("own", "coords", lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)
    return match_nodes(left, docs.withColumnRenamed("doc_id", "loc_id"), "block", F.greatest(F.lit(0.0), F.lit(1.0) - MATCH_SLOPE * gap))


def _chunks(rows: DataFrame, coords: Column, key: list[str]) -> DataFrame:
    return chunk_nodes(rows, key, coords)


WORKLOADS = {
    "tower": (3, lambda s, d: pack(tower_realisations(s, d))),
    "cover": (55, lambda s, d: _chunks(*cover_points(s, d), LINE_KEY)),
    "census": (68, lambda s, d: _chunks(*census_points(s, d), LINE_KEY)),
    "cross": (57, lambda s, d: _chunks(*big_cross_points(s, d), ["p_partkey", "s_suppkey"])),
    "descriptors": (64, lambda s, d: pack(chunk_realisations(descriptor_points(s, d), ["vec_id"], F.col("coords")))),
    "descriptors_pair": (128, lambda s, d: pack(chunk_realisations(descriptor_points(s, d, True), ["vec_id"], F.col("coords")))),
    "lines": (4, lambda s, d: pack(line_realisations(s, d))),
    "orders": (4, lambda s, d: pack(order_realisations(s, d))),
    "orders_absent": (4, lambda s, d: pack(order_realisations(s, d, True))),
    "parts": (4, lambda s, d: pack(keyed_lines(s, d, "l_partkey"))),
    "suppliers": (4, lambda s, d: pack(keyed_lines(s, d, "l_suppkey"))),
    "users": (3, lambda s, d: pack(user_realisations(s, d))),
    "customers": (2, lambda s, d: pack(customer_realisations(s, d))),
    "matches": (8, lambda s, d: pack(match_realisations(s, d))),
}


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, int]:
    """(packed nodes written once, dimension)."""
    d, build = WORKLOADS[name]
    return kept(build(spark, sf_dir), name), d


def hash_centres(realisations: DataFrame, k: int, seed: int = 5) -> list[list[float]]:
    """k locations by least portable uniform of their id: a fixed centre set for cost tests."""
    rows = realisations.select(portable_uniform(seed, "loc_id", 0).alias("u"), "loc_id", "coords").distinct().orderBy("u", "loc_id").limit(k).collect()
    return [list(x["coords"]) for x in rows]
