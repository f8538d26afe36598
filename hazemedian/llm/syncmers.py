"""Document fingerprints of closed syncmers, with DataFrame functions only.

A text's units are its words (runs of letters and digits, lower-cased) in pieces of at most UNIT characters from the word's start,
and each Han or kana character by itself; one rule for texts of all lengths and scripts.
A k-mer of units is an anchor if the smallest hash among its s-mers stands first or last in it.  Whether it is one
depends on its own units alone, so equal passages have equal anchors wherever they stand, and every k - s
neighbouring k-mers hold one.  A text with units but without an anchor (it has fewer than 2k - s - 1 units) has one, its whole.

The fingerprint is the sequence of the anchors' 32-bit hashes in order of position, eight hexadecimal digits each; the likeness of two
texts is the Jaccard similarity of the sets of anchors in their fingerprints.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, narrow

K, S = 6, 2
UNIT = 4
CELLS = 4096
BUCKET_BYTES = 16 << 20
_UNIT = r"[\p{IsHan}\p{IsHiragana}\p{IsKatakana}]|[\p{L}\p{N}&&[^\p{IsHan}\p{IsHiragana}\p{IsKatakana}]]{1,%d}" % UNIT


def _let(value: Column, body) -> Column:
    """body(value), where value is computed once however often body uses it."""
    return F.transform(F.array(value), body)[0]


def _places(last: Column) -> Column:
    return F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))


def anchors(units: Column, k: int = K, s: int = S) -> Column:
    """array<struct<position int, hash int>> of the closed syncmers of an array of units."""

    def of(u: Column) -> Column:
        smers = F.transform(_places(F.size(u) - s), lambda i: F.xxhash64(*(F.get(u, i + j) for j in range(s))))

        def closed(g: Column) -> Column:
            span = k - s
            chosen = F.filter(_places(F.size(u) - k), lambda i: F.least(F.get(g, i), F.get(g, i + span)) <= (F.least(*(F.get(g, i + j) for j in range(1, span))) if span > 2 else F.get(g, i + 1)))
            steps = sorted({*range(0, span, s), span})
            return F.transform(chosen, lambda i: F.struct(i.alias("position"), F.hash(*(F.get(g, i + j) for j in steps)).alias("hash")))

        none = F.array().cast("array<struct<position:int,hash:int>>")
        whole = F.when(F.size(u) > 0, F.array(F.struct(F.lit(0).alias("position"), F.hash(F.concat_ws(" ", u)).alias("hash")))).otherwise(none)
        found = F.when(F.size(u) >= k, _let(smers, closed)).otherwise(none)
        return _let(found, lambda x: F.when(F.size(x) > 0, x).otherwise(whole))

    return _let(units, of)


def units_of(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(_UNIT), F.lit(0))


def hashes_of(text: Column) -> Column:
    """array<int>: a text's anchors in order of position."""
    return F.transform(anchors(units_of(text)), lambda a: a["hash"])


def fingerprint_of(hashes: Column) -> Column:
    """Eight hexadecimal digits for each anchor."""
    return F.array_join(F.transform(hashes, lambda h: F.lpad(F.hex(h.cast("long").bitwiseAND(F.lit(0xFFFFFFFF))), 8, "0")), "")


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two anchor sets; 1 for two texts without anchors."""
    both = F.size(F.array_intersect(a, b))
    return F.coalesce(F.try_divide(both.cast("double"), F.size(F.array_union(a, b)).cast("double")), F.lit(1.0))


def _bucketed(docs: DataFrame) -> tuple[Column, int]:
    """(expression of a bucket that ascends with doc_id, number of buckets), about BUCKET_BYTES of text a bucket.

    Ids are counted in CELLS equal ranges.  Runs of thin ranges make one bucket, a dense one is cut into equal parts, so
    that neither gaps between ids nor the size of the table matter.
    """
    low, high, total = docs.agg(F.min("doc_id"), F.max("doc_id"), F.sum(F.octet_length("text"))).first()
    if low is None:
        return F.lit(0), 1
    shift = 2 if high - low >= 1 << 62 else 0  # differences of any two ids must be numbers of 64 bits
    low, high = low >> shift, high >> shift
    width = (high - low) // CELLS + 1
    place = F.shiftright("doc_id", shift) - F.lit(low).cast("long")
    cell = F.expr(f"(shiftright(doc_id, {shift}) - {low}L) div {width}L").cast("int")
    counts = {x["c"]: x["n"] for x in docs.groupBy(cell.alias("c")).agg(F.count("*").alias("n")).collect()}
    most = -(-sum(counts.values()) // max(1, -(-int(total or 0) // BUCKET_BYTES)))
    of, steps, bucket, held = [], [], 0, 0
    for k in range(CELLS):
        n = counts.get(k, 0)
        if held and n and held + n > most:
            bucket, held = bucket + 1, 0
        of.append(bucket)
        parts = max(1, -(-n // most))
        steps.append(width // parts + 1)
        if parts > 1:
            bucket, held = bucket + parts, 0
        else:
            held += n
    inside = F.call_function("div", place - cell.cast("long") * F.lit(width).cast("long"), F.get(F.lit(steps).cast("array<bigint>"), cell))
    return F.get(F.lit(of), cell) + inside.cast("int"), bucket + 1


def with_next(docs: DataFrame, carried: list[str]) -> DataFrame:
    """`docs(doc_id, text, ...)` with next_<column> of the document that follows in descending doc_id order.

    After the last comes the first.  One shuffle by ranges of doc_id; a range's last document finds the next range's first
    in a copy that is dealt to its own range.
    """
    bucket, _ = _bucketed(docs.select("doc_id", "text"))
    heads = docs.select("doc_id", bucket.cast("int").alias("b")).groupBy("b").agg(F.max("doc_id").alias("doc_id"))
    after = F.coalesce(F.lead("b").over(Window.orderBy("b")), F.min("b").over(Window.partitionBy()))
    to = Scratch(docs.sparkSession).keep(heads.select("doc_id", after.alias("bucket")), "heads")  # one row a bucket
    copies = docs.join(narrow(to), "doc_id").withColumn("copy", F.lit(1))
    rows = docs.withColumn("bucket", bucket.cast("int")).withColumn("copy", F.lit(0)).unionByName(copies)
    order = Window.partitionBy("bucket").orderBy("copy", F.col("doc_id").desc(), "text")
    return rows.select("*", *(F.lead(c).over(order).alias(f"next_{c}") for c in carried)).where("copy = 0").drop("copy", "bucket")


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of every row.

    The edited text has its last floor(n_chars / 2) characters replaced by the first as many of the next
    document in descending doc_id order.  Null texts are empty; a text without letters and digits has an empty fingerprint,
    and two of these are alike; very long texts have as many anchors as they need; rows with a null doc_id have no place in the order and are left out; repeated rows follow each other; an empty table
    gives no row; other columns are not read.
    """
    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).where("doc_id is not null")
    if rows.isEmpty():
        return rows.select("doc_id", F.lit(0).cast("long").alias("n_chars"), *(F.lit("").alias(c) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")), *(F.lit(0.0).alias(c) for c in ("near_edited", "near_next")))
    rows = with_next(rows.withColumn("own", hashes_of(F.col("text"))), ["text", "own"])
    n = F.char_length("text").cast("long")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), (n - half).cast("int")), F.substring("next_text", F.lit(1), half))
    rows = rows.select("doc_id", n.alias("n_chars"), edited.alias("edited"), "own", "next_own").withColumn("other", hashes_of(F.col("edited")))
    return rows.select("doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), fingerprint_of(F.col("own")).alias("fingerprint"), fingerprint_of(F.col("other")).alias("edited_fingerprint"), likeness(F.col("own"), F.col("other")).alias("near_edited"), likeness(F.col("own"), F.col("next_own")).alias("near_next"))
