"""Toxicity by a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Features are the presence of character n-grams (5, 7 and 9 code points of the text with A-Z lower-cased and
every other ASCII mark as a blank, one blank at either end), hashed to 2^20.  A feature's value is its log-count ratio, the log of its
smoothed share among toxic documents over that among others; a document's values are scaled to unit length, and logistic
regression on them is fitted by gradient steps of one rate over batches of documents, so that features of few documents
move little.  Every feature takes part.

The classifier is fitted on a bounded sample: of the MOST_TOXIC toxic and MOST_OTHER other training documents whose
hashed doc_id is smallest those, in this order, that begin within TOXIC_BYTES and OTHER_BYTES of text, whole, with class
weights that restore the share of toxic documents among all training labels.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import held_by_worker, held_out, slices, text_buffer, tidy, trim

ORDERS = (5, 7, 9)
BITS = 20
MOST_TOXIC, MOST_OTHER = 2_500, 5_000
SMOOTHING, RATE = 8.0, 60.0
#: Odd: strong ratios count for more, weak ones for little, none for nothing.
POWER = 3
TOXIC_BYTES, OTHER_BYTES = 2 << 20, 4 << 20
ROUNDS, LEAST_STEPS, BATCH_DOCUMENTS = 8, 100, 96

_CLASS = np.arange(128, dtype=np.uint32)
_CLASS[65:91] += 32
_CLASS[[k for k in range(128) if not chr(k).isalnum()]] = 32
_STEP = np.random.Generator(np.random.PCG64(99)).integers(1, 2**63, max(ORDERS), dtype=np.uint64) | np.uint64(1)


def grams(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature) of every n-gram of a string column, ascending and without repeats."""
    data, offsets = text_buffer(column)
    points = np.frombuffer(data.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32)
    before = np.zeros(len(data) + 1, np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=before[1:])
    bounds = before[offsets]
    n = len(bounds) - 1
    row_of = np.repeat(np.arange(n), np.diff(bounds))
    padded = np.full(len(points) + 2 * n, 32, np.uint32)
    padded[np.arange(len(points)) + 2 * row_of + 1] = np.where(points < 128, _CLASS[points & 127], points)
    rows = np.repeat(np.arange(n), np.diff(bounds) + 2)
    codes = (padded.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    codes ^= codes >> np.uint64(29)
    found, total = [], np.zeros(len(codes), np.uint64)
    kind = np.uint32 if n <= 1 << 32 - BITS else np.uint64
    for k in range(max(ORDERS)):
        m = len(codes) - k
        if m <= 0:
            break
        total = total[:m] + codes[k:] * _STEP[k]
        if k + 1 in ORDERS:
            feature = ((total + np.uint64(k)) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(64 - BITS)).astype(kind)
            found.append((rows[:m].astype(kind) << kind(BITS) | feature)[rows[:m] == rows[k:]])
    keys = np.concatenate(found) if found else np.zeros(0, kind)
    keys.sort()
    keys = keys[np.r_[True, keys[1:] != keys[:-1]]] if len(keys) else keys
    return (keys >> kind(BITS)).astype(np.int32), (keys & kind((1 << BITS) - 1)).astype(np.int32)


def fit(texts: pa.Array, toxic: np.ndarray, share: float) -> dict:
    """ratios, weights (of all 2^BITS features) and bias; `share` is the share of toxic documents to be restored."""
    ones, rest = np.zeros((2, 1 << BITS), np.int32)
    sizes, columns, start = [], [], 0
    for part in slices(pa.record_batch({"text": texts})):
        rows, features = grams(part.column("text"))
        label = toxic[start + rows]
        ones += np.bincount(features[label == 1], minlength=1 << BITS).astype(np.int32)
        rest += np.bincount(features[label == 0], minlength=1 << BITS).astype(np.int32)
        sizes.append(np.bincount(rows, minlength=part.num_rows))
        columns.append(features)
        start += part.num_rows
    n, n1 = len(toxic), int(toxic.sum())
    # Pseudo-documents in the classes' own shares: a feature of one document says little, whichever class is larger.
    shares = (ones + SMOOTHING * n1 / n) / max(n1, 1), (rest + SMOOTHING * (n - n1) / n) / max(n - n1, 1)
    ratio = ((np.log(shares[0]) - np.log(shares[1])) ** POWER).astype(np.float32)
    bounds = np.r_[0, np.cumsum(np.concatenate(sizes))]
    column = np.concatenate(columns)
    del columns
    each = np.where(toxic == 1, share * n / max(n1, 1), (1 - share) * n / max(n - n1, 1))
    # Dealt anew in a fixed order, so that each batch holds both classes.
    batches = np.array_split(np.random.default_rng(5).permutation(n), max(1, -(-n // BATCH_DOCUMENTS)))
    weight, bias = np.zeros(1 << BITS, np.float32), float(np.log(share / (1 - share)))
    for _ in range(max(ROUNDS, -(-LEAST_STEPS // len(batches)))):
        for batch in batches:
            count = bounds[batch + 1] - bounds[batch]
            doc = np.repeat(np.arange(len(batch)), count)
            own = column[np.arange(len(doc)) + np.repeat(bounds[batch] - (np.cumsum(count) - count), count)]
            value = ratio[own]
            length = np.sqrt(np.bincount(doc, value * value, minlength=len(batch)))
            value = value / np.where(length > 0, length, 1)[doc]
            z = np.clip(np.bincount(doc, weight[own] * value, minlength=len(batch)) + bias, -30, 30)
            error = (1 / (1 + np.exp(-z)) - toxic[batch]) * each[batch] / len(batch)
            slope = np.bincount(own, error[doc] * value, minlength=1 << BITS).astype(np.float32)
            weight -= np.float32(RATE) * slope
            bias -= RATE * error.sum()
    return {"ratios": ratio, "weights": weight, "bias": bias}


def train(docs: DataFrame, labels: DataFrame) -> dict | None:
    """The model from `labels(doc_id, toxic)` of documents that are not held out; None if a class is missing.

    Rows without doc_id or label are not used; of several labels of a document the largest counts.
    """
    known = labels.select(F.col("doc_id").cast("long"), F.col("toxic").cast("int")).where("doc_id is not null and toxic is not null").where(~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    n, n1 = known.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    if n1 == 0 or n1 == n:
        return None
    share = n1 / n
    chosen = [known.where(F.col("toxic") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most) for k, most in ((1, MOST_TOXIC), (0, MOST_OTHER))]
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    sample = rows.join(F.broadcast(chosen[0].union(chosen[1])), "doc_id")  # at most MOST_TOXIC + MOST_OTHER ids
    # The bytes before each of these documents, an id that several rows share counted as one; then whole documents only.
    sizes = sample.groupBy("toxic", "doc_id").agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("size"))
    order = Window.partitionBy("toxic").orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum("size").over(order), F.lit(0))
    taken = sizes.withColumn("before", before).where(F.col("before") < F.when(F.col("toxic") == 1, TOXIC_BYTES).otherwise(OTHER_BYTES))
    sample = rows.join(F.broadcast(taken.select("doc_id", "toxic")), "doc_id")

    def fitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_by_worker(("fit",), dict)
        held = [batch for batch in batches if batch.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held)
        del held
        # One order for any arrival of the rows, so that a retried task fits the same model.
        order = pc.sort_indices(table, [("doc_id", "ascending"), ("text", "ascending")])
        table = table.take(order).combine_chunks()
        model = fit(table.column("text").chunk(0), table.column("toxic").to_numpy(), share)
        yield pa.record_batch({"ratios": [model["ratios"].tobytes()], "weights": [model["weights"].tobytes()], "bias": [model["bias"]]})

    row = sample.repartition(1).mapInArrow(tidy(fitted), "ratios binary, weights binary, bias double").first()
    return None if row is None else {"ratios": np.frombuffer(row["ratios"], np.float32), "weights": np.frombuffer(row["weights"], np.float32), "bias": row["bias"]}


def scores(column: pa.Array, model: dict) -> np.ndarray:
    ratio, weight = model["ratios"], model["weights"]
    out = []
    for part in slices(pa.record_batch({"text": column})):
        rows, features = grams(part.column("text"))
        value = ratio[features]
        length = np.sqrt(np.bincount(rows, value * value, minlength=part.num_rows))
        total = np.bincount(rows, value * weight[features], minlength=part.num_rows) / np.where(length > 0, length, 1)
        out.append(1 / (1 + np.exp(-np.clip(total + model["bias"], -30, 30))))
    return np.concatenate(out) if out else np.zeros(0)


def score_column(model: dict | None, text: Column, spark) -> Column:
    """The toxicity of a text column, 0 to 1; without a model 0."""
    if model is None:
        return F.lit(0.0)
    name = uuid.uuid4().hex
    sent = spark.sparkContext.broadcast(model)  # 8 bytes for each of the 2^BITS features

    def of(column: pa.Array) -> pa.Array:
        model = held_by_worker(("toxicity", name), lambda: sent.value)
        found = pa.array(scores(column, model), pa.float64())
        trim()
        return found

    return F.arrow_udf(of, "double")(text.cast("string"))


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of `docs`.

    Null and empty texts get the score of a text of one blank on either side, which has no features (the model's bias); a
    null doc_id stays null and isn't held out; repeated rows each give a row; a very long text is scored whole, as a
    slice by itself; a score of exactly 0.5 predicts 1; empty tables give no row; without labels of both classes every
    score is 0; other columns are not read.
    """
    model = train(docs, labels)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    scored = rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), score_column(model, F.col("text"), docs.sparkSession).alias("score"))
    return scored.withColumn("predicted", F.when(F.col("score") >= 0.5, 1).otherwise(0))
