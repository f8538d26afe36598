"""Substring dedup by content-defined chunking.

A gear rolling hash runs over the UTF-8 bytes; a chunk may end where the hash's top bits are zero, at least
MIN_BYTES after the last end, and must end at MAX_BYTES, in both cases before a whole character.  Ends depend on the last bytes
alone, so an insertion moves the ends near it and no others.  Equal chunks (16-byte digests) are repeats; neighbouring repeats are one
passage.  Expected chunks of about 55 bytes let a passage of 50 words hold several whole chunks.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ROW_KEY, Scratch, free_name, keyed, slices, text_buffer, tidy

MIN_BYTES, MEAN_BITS, MAX_BYTES = 24, 5, 1024
#: A passage is reported from so many repeated bytes.
PASSAGE_BYTES = 64
GEAR = np.random.Generator(np.random.PCG64(4242)).integers(0, 2**32, 256, dtype=np.uint32)
_WINDOW = 32


def gear_hash(data: np.ndarray) -> np.ndarray:
    """The 32-bit gear hash at every byte: sum of GEAR[byte] shifted once for each later byte, by doubling."""
    h, width = GEAR[data], 1
    while width < _WINDOW:
        h[width:] = h[width:] + (h[:-width] << np.uint32(width))
        width *= 2
    return h


def chunk_ends(data: np.ndarray) -> list[int]:
    """Ends of a text's chunks; the last may be short.  In the first bytes the hash's window is that much shorter."""
    opens = np.r_[(data & 0xC0) != 0x80, True]
    possible = np.flatnonzero((gear_hash(data) >> np.uint32(32 - MEAN_BITS) == 0) & opens[1:]) + 1
    ends, last, n = [], 0, len(data)

    def forced(last: int) -> int:
        stop = last + MAX_BYTES
        while not opens[stop]:
            stop -= 1
        return stop

    for at in possible.tolist():
        while at - last > MAX_BYTES:
            last = forced(last)
            ends.append(last)
        if at - last >= MIN_BYTES:
            ends.append(at)
            last = at
    while n - last > MAX_BYTES:
        last = forced(last)
        ends.append(last)
    if last < n:
        ends.append(n)
    return ends


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every chunk of every row, a text's short last one too; rows without a key get one of task and place."""
    seen = TaskContext.get().partitionId() << 33
    for batch in batches:
        for part in slices(batch):
            data, offsets = text_buffer(part.column("text"))
            raw = data.tobytes()
            names = part.column("doc_id").to_pylist()
            keys = part.column("row").to_pylist()
            ids, rows, begins, stops, digests = [], [], [], [], []
            for k, name in enumerate(names):
                base, end = int(offsets[k]), int(offsets[k + 1])
                last = base
                own = seen if keys[k] is None else keys[k]
                seen += 1
                for stop in chunk_ends(data[base:end]):
                    stop += base
                    ids.append(name)
                    rows.append(own)
                    begins.append(last - base)
                    stops.append(stop - base)
                    digests.append(hashlib.blake2b(raw[last:stop], digest_size=16).digest())
                    last = stop
            pairs = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
            yield pa.record_batch({"doc_id": pa.array(ids, pa.int64()), "row": pa.array(rows, pa.int64()), "begin": pa.array(begins, pa.int64()), "stop": pa.array(stops, pa.int64()), "high": pa.array(np.ascontiguousarray(pairs[:, 0])), "low": pa.array(np.ascontiguousarray(pairs[:, 1]))})


def repeated_passages(docs: DataFrame, passage_bytes: int = PASSAGE_BYTES) -> DataFrame:
    """Every passage of at least `passage_bytes` UTF-8 bytes whose chunks all occur more than once:
    doc_id, begin, stop (byte offsets), chunks, first_doc_id (smallest document of the chunks' first
    occurrences), removed_bytes (bytes of it that an earlier occurrence stands for), removed (array of their
    (begin, stop) in order, touching ones joined).

    Occurrences are ordered by doc_id, row and offset, the first of each chunk is kept.  Null and empty texts have
    no chunk; repeated rows and rows that share a doc_id are rows like others, the later ones copies of the first; rows with a null doc_id are left out;
    a very long text is one slice; an empty table gives no row; other columns are not read.
    """
    rows = docs.select(F.col("doc_id").cast("long"), F.lit(None).cast("long").alias("row"), F.col("text").cast("string")).where("doc_id is not null")
    return _passages(rows, passage_bytes).drop("row")


def _passages(rows: DataFrame, passage_bytes: int) -> DataFrame:
    """`repeated_passages` of (doc_id, row, text), with `row`; null doc_ids come last."""
    scratch = Scratch(rows.sparkSession)
    chunks = scratch.keep(rows.mapInArrow(tidy(_chunks), "doc_id long, row long, begin long, stop long, high long, low long"), "chunks")
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row", "begin")
    firsts = chunks.groupBy("high", "low").agg(F.count("*").alias("times"), F.min(place).alias("first")).where("times > 1").drop("times")
    found = chunks.join(scratch.keep(firsts, "firsts"), ["high", "low"]).select("doc_id", "row", "begin", "stop", ((F.col("row") == F.col("first.row")) & (F.col("begin") == F.col("first.begin"))).alias("kept"), F.col("first.doc_id").alias("first_doc"))

    # A row's repeated chunks are grouped in its own row; runs of touching chunks make passages.
    of = found.groupBy("doc_id", "row").agg(F.sort_array(F.collect_list(F.struct("begin", "stop", "kept", "first_doc"))).alias("c"))

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for row in batch.to_pylist():
                run: list = []
                for c in [*row["c"], None]:
                    if run and (c is None or c["begin"] != run[-1]["stop"]):
                        gone: list = []
                        for x in run:
                            if not x["kept"]:
                                touches = gone and gone[-1]["stop"] == x["begin"]
                                begin = gone.pop()["begin"] if touches else x["begin"]
                                gone.append({"begin": begin, "stop": x["stop"]})
                        out.append((row["doc_id"], row["row"], run[0]["begin"], run[-1]["stop"], len(run), min((x["first_doc"] for x in run if x["first_doc"] is not None), default=None), sum(x["stop"] - x["begin"] for x in gone), gone))
                        run = []
                    if c is not None:
                        run.append(c)
            names = ("doc_id", "row", "begin", "stop", "chunks", "first_doc_id", "removed_bytes")
            removed = pa.array([x[-1] for x in out], pa.list_(pa.struct([("begin", pa.int64()), ("stop", pa.int64())])))
            yield pa.record_batch({name: pa.array([x[k] for x in out], pa.int64()) for k, name in enumerate(names)} | {"removed": removed})

    found = of.mapInArrow(runs, "doc_id long, row long, begin long, stop long, chunks long, first_doc_id long, removed_bytes long, removed array<struct<begin:long,stop:long>>")
    return found.where(F.col("stop") - F.col("begin") >= passage_bytes)


def without_repeated_passages(docs: DataFrame, passage_bytes: int = PASSAGE_BYTES) -> DataFrame:
    """`docs` with the parts of repeated passages cut out that an earlier occurrence stands for.

    Rows are told apart by a row_key, so that null and repeated doc_ids are rows like others (null ones come last in the order
    of occurrences) and a row loses its own repeats only; of equal rows the later keep what is not in a passage.  Null texts stay null, a text that is a
    copy becomes empty; empty tables stay empty; all columns stay, whatever their names.
    """
    rows = keyed(docs)
    spans, key = free_name(rows, "spans"), rows[ROW_KEY]
    gone = _passages(rows.select(F.col("doc_id").cast("long"), key.alias("row"), F.col("text").cast("string")), passage_bytes).select("row", F.explode("removed").alias("span"))
    gone = gone.groupBy(F.col("row").alias(ROW_KEY)).agg(F.sort_array(F.collect_list("span")).alias(spans))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, gaps in zip(batch.column("text").to_pylist(), batch.column(spans).to_pylist(), strict=True):
                if text is not None and gaps:
                    raw, edges = text.encode(), [0, *(x for gap in gaps for x in (gap["begin"], gap["stop"])), None]
                    text = b"".join(raw[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)).decode()
                texts.append(text)
            at = batch.schema.get_field_index("text")
            yield batch.set_column(at, "text", pa.array(texts, pa.string())).drop_columns([spans])

    return rows.join(gone, ROW_KEY, "left").select(*docs.columns, spans).mapInArrow(cut, docs.schema)
