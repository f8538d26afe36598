"""Language identification by words first, then ever shorter character n-grams.

A known word scores its smoothed log frequency in each language.  An unseen word backs off: the mean log
frequency of those of its n-grams (with word edges) that are known, of the greatest n from 5 down to 1 for which
any is; a word without a known character says nothing.  A text takes the language of the greatest sum.

The counts come from a bounded sample: of the MOST_DOCUMENTS training documents whose hashed doc_id is smallest those,
in this order, that begin within MOST_BYTES of text, whole.  The model keeps every word and n-gram of the sample.
"""

from __future__ import annotations

import pickle
import re
import uuid
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import held_by_worker, held_out, slices, tidy

MOST_DOCUMENTS, MOST_BYTES = 6_000, 6 << 20
LONGEST = 5
SMOOTHING = 0.1
#: Unseen words whose scores a worker remembers.
MOST_REMEMBERED = 300_000

_WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def has_letter(word: str) -> bool:
    return word.isalpha() or any(map(str.isalpha, word))


def grams_of(word: str, n: int) -> list[str]:
    marked = f"<{word}>" if n > 1 else word
    return [marked[k : k + n] for k in range(len(marked) - n + 1)]


def _logs(counts: list[Counter], keys: list[str]) -> np.ndarray:
    """A row for each key: its smoothed log frequency in each language."""
    table = np.array([[c[key] for c in counts] for key in keys], float).reshape(len(keys), len(counts))
    whole = np.array([sum(c.values()) for c in counts], float)
    return np.log((table + SMOOTHING) / (whole + SMOOTHING * max(len(keys), 1))).astype(np.float32)


def _all(counts: list[Counter]) -> list[str]:
    return sorted(set().union(*counts))


def fit(texts: list[str | None], langs: list[str]) -> dict:
    names = sorted(set(langs))
    at = {name: k for k, name in enumerate(names)}
    words: list[Counter] = [Counter() for _ in names]
    for text, lang in zip(texts, langs, strict=True):
        words[at[lang]].update(words_of(text or ""))
    known = _all(words)
    model = {"names": names, "words": (known, _logs(words, known)), "grams": []}
    for n in range(1, LONGEST + 1):
        # Types count, not tokens: unseen words look like rare words, not like frequent ones.
        grams: list[Counter] = [Counter() for _ in names]
        for own, c in zip(words, grams, strict=True):
            for word in own:
                c.update(grams_of(word, n))
        known = _all(grams)
        model["grams"].append((known, _logs(grams, known)))
    return model


def train(docs: DataFrame) -> dict | None:
    """The model from text and non-null lang of documents that are not held out; None if there are none."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.col("lang").cast("string")).where("doc_id is not null and lang is not null and text is not null").where(~held_out(F.col("doc_id")))
    chosen = rows.select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(MOST_DOCUMENTS).distinct()
    sample = rows.join(F.broadcast(chosen), "doc_id")  # at most MOST_DOCUMENTS ids
    sizes = sample.groupBy("doc_id").agg(F.sum(F.octet_length("text")).alias("size"))
    before = F.coalesce(F.sum("size").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sample = rows.join(F.broadcast(sizes.withColumn("before", before).where(F.col("before") < MOST_BYTES).select("doc_id")), "doc_id")

    def fitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = sorted((row["doc_id"], row["text"], row["lang"]) for batch in batches for row in batch.to_pylist())
        if found:
            yield pa.record_batch({"model": pa.array([pickle.dumps(fit([x[1] for x in found], [x[2] for x in found]))], pa.binary())})

    row = sample.repartition(1).mapInArrow(tidy(fitted), "model binary").first()
    return None if row is None else pickle.loads(row["model"])


class Scorer:
    def __init__(self, model: dict):
        self.names = model["names"]
        self.known = dict(zip(model["words"][0], range(len(model["words"][0])), strict=True))
        self.grams = [(dict(zip(keys, range(len(keys)), strict=True)), table) for keys, table in model["grams"]]
        self.base = model["words"][1]
        self.reset()

    def reset(self) -> None:
        self.place = dict(self.known)
        self.table = np.zeros((len(self.base) + (1 << 12), len(self.names)), np.float32)
        self.table[: len(self.base)] = self.base
        self.used = len(self.base)

    def back_off(self, word: str) -> np.ndarray:
        for known, table in reversed(self.grams):
            n = len(next(iter(known), ""))
            found = [known[x] for x in grams_of(word, n) if x in known] if n else []
            if found:
                return table[found].mean(0)
        return np.zeros(len(self.names))

    def __call__(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        cut = [words_of(x) if x else [] for x in texts]
        if self.used > len(self.base) + MOST_REMEMBERED:
            self.reset()
        new: set = set()
        for words in cut:
            new.update(words)
        for word in new - self.place.keys():
            if self.used == len(self.table):
                self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.table[self.used] = self.back_off(word)
            self.place[word] = self.used
            self.used += 1
        langs, sure, get = [], np.zeros(len(texts)), self.place.__getitem__
        for k, words in enumerate(cut):
            if not any(map(has_letter, words)):
                langs.append("und")
                continue
            total = self.table[np.fromiter(map(get, words), np.int64, len(words))].sum(0, dtype=float)
            best = int(total.argmax())
            langs.append(self.names[best])
            sure[k] = 1 / np.exp((total - total[best]) / len(words) ** 0.5).sum()
        return langs, sure


def predict_column(model: dict | None, text: Column, spark) -> Column:
    """struct(lang_pred, score) of a text column."""
    if model is None:
        return F.struct(F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"))
    sent, name = spark.sparkContext.broadcast(model), uuid.uuid4().hex

    def of(column: pa.Array) -> pa.Array:
        scorer = held_by_worker(("languages", name), lambda: Scorer(sent.value))
        langs, sure = [], [np.zeros(0)]
        for part in slices(pa.record_batch({"text": column})):
            own = scorer(part.column("text").to_pylist())
            langs += own[0]
            sure.append(own[1])
        return pa.StructArray.from_arrays([pa.array(langs, pa.string()), pa.array(np.concatenate(sure))], ["lang_pred", "score"])

    return F.arrow_udf(of, "lang_pred string, score double")(text.cast("string"))


def languages(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row of `docs`.

    `und` and 0 for null texts, texts without a letter, and where nothing could be learnt; a null doc_id stays
    null and isn't held out; rows with a null lang are predicted, not learnt from; repeated rows each give a
    row; ties go to the first language by name; an empty table gives no row; other columns are not read.
    """
    model = train(docs)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    scored = rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), predict_column(model, F.col("text"), docs.sparkSession).alias("p"))
    return scored.select("doc_id", "held_out", "p.lang_pred", "p.score")
