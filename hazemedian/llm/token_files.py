"""Token-ID output: one concatenated id array with Elias-Fano encoded document boundaries.

File format.  A data set is a Parquet folder of blocks in ascending doc_id order; each row is one block:

    part int, seq int          place of the block: range partition, then number inside it
    first_doc long             smallest doc_id inside
    n_docs long, n_ids long    documents and ids inside
    doc_ids binary             Elias-Fano code of the ascending doc_ids minus first_doc
    bounds binary              Elias-Fano code of the n_docs+1 offsets of the documents in the id array
    ids binary                 all ids, little-endian unsigned, 16 bits if the vocabulary allows, else 32

The Elias-Fano code holds, after a header (count, universe, low width as three uint64), the low bits of all
values packed and the high bits as unary bit vector, about 2 + log2(universe/count) bits a value; `select`
finds a value by the position of its one bit, over a directory of each 512th one bit made on reading.  No
offset table is stored; `read_documents` finds single documents by bisection over select, whole reads decode a block
in order.  Spark's committer writes the blocks, so the store may be any that Spark can
write, a lost executor's blocks are written again, and a reader never sees half of them.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, narrow, slices, tidy
from .tokens import VOCABULARY, encoder, vocabulary_path

END_ID = 2
BLOCK_IDS = 1 << 19
PARTITION_BYTES = 16 << 20
_SAMPLE = 512
_BITS = np.array([bin(k).count("1") for k in range(256)], np.uint32)

BLOCK_SCHEMA = "part int, seq int, first_doc long, n_docs long, n_ids long, width int, doc_ids binary, bounds binary, ids binary"


class EliasFano:
    """A non-decreasing sequence of integers below `universe`."""

    def __init__(self, n: int, universe: int, low_bits: int, low: np.ndarray, high: np.ndarray):
        self.n, self.universe, self.low_bits, self.low, self.high = n, universe, low_bits, low, high
        self._ones = None

    @classmethod
    def encode(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n, universe = len(values), int(values[-1]) + 1 if len(values) else 1
        low_bits = max(0, (universe // max(n, 1)).bit_length() - 1)
        bits = np.unpackbits(values.astype("<u8").view(np.uint8).reshape(n, 8)[:, : (low_bits + 7) // 8], axis=1, count=low_bits, bitorder="little") if low_bits else np.zeros(0, np.uint8)
        at = (values >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        high = np.zeros(int(at[-1]) + 1 if n else 0, np.uint8)
        high[at] = 1
        return cls(n, universe, low_bits, np.packbits(bits, bitorder="little"), np.packbits(high, bitorder="little"))

    def to_bytes(self) -> bytes:
        return np.array([self.n, self.universe, self.low_bits], "<u8").tobytes() + self.low.tobytes() + self.high.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> EliasFano:
        n, universe, low_bits = (int(x) for x in np.frombuffer(data, "<u8", 3))
        cut = 24 + (n * low_bits + 7) // 8
        return cls(n, universe, low_bits, np.frombuffer(data, np.uint8, cut - 24, 24), np.frombuffer(data, np.uint8, -1, cut))

    def _low(self, k: np.ndarray) -> np.ndarray:
        total = np.zeros(len(k), np.uint64)
        for bit in range(self.low_bits):
            at = k * self.low_bits + bit
            total |= ((self.low[at >> 3] >> (at & 7).astype(np.uint8)) & 1).astype(np.uint64) << np.uint64(bit)
        return total

    def _directory(self) -> np.ndarray:
        """The byte of each _SAMPLE-th one bit and the one bits before it, 64 bits a sample, made on the first select."""
        if self._ones is None:
            counts = np.cumsum(_BITS[self.high], dtype=np.uint32)
            byte = np.searchsorted(counts, np.arange(0, max(self.n, 1), _SAMPLE), side="right").astype(np.uint32)
            self._ones = np.stack([byte, counts[byte] - _BITS[self.high[byte]]]) if self.n else np.zeros((2, 0), np.uint32)
        return self._ones

    def select(self, k: int) -> int:
        """The k-th value, from the position of the k-th one bit, searched from the sample before it."""
        if not 0 <= k < self.n:
            raise IndexError(k)
        byte, left = (int(x) for x in self._directory()[:, k // _SAMPLE])
        left = k - left
        while True:
            counts = np.cumsum(_BITS[self.high[byte : byte + _SAMPLE]], dtype=np.int64)
            if left < counts[-1]:
                break
            byte, left = byte + _SAMPLE, left - int(counts[-1])
        step = int(np.searchsorted(counts, left, side="right"))
        left, byte = left - (int(counts[step - 1]) if step else 0), byte + step
        at = 8 * byte + int(np.flatnonzero(np.unpackbits(self.high[byte : byte + 1], bitorder="little"))[left])
        return (at - k) << self.low_bits | int(self._low(np.array([k]))[0])

    def place_of(self, value: int) -> int:
        """The first k whose value is `value` or more, by bisection with select."""
        low, high = 0, self.n
        while low < high:
            mid = (low + high) // 2
            low, high = (mid + 1, high) if self.select(mid) < value else (low, mid)
        return low

    def values(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n]
        k = np.arange(self.n)
        return ((ones - k).astype(np.uint64) << np.uint64(self.low_bits) | self._low(k)).astype(np.int64)


def write_token_files(docs: DataFrame, path: str, vocabulary: str = VOCABULARY, end_id: int = END_ID) -> None:
    """Writes the ids of every text, each with `end_id` after it, in ascending doc_id order.

    A null text is empty and gives the end id alone.  Rows without doc_id come first and are stored under the
    id -1 less than the smallest of their block; documents that share an id stand beside each other, in the
    order of their texts' hashes.  A very long text makes a longer block.  An empty table gives a data set without
    blocks.  Other columns are not read.
    """
    vocabulary = vocabulary_path(vocabulary)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    order = ["doc_id", F.xxhash64("text")]  # an id that many rows share is dealt by its texts
    ordered = rows.repartitionByRange(max(1, -(-int(total) // PARTITION_BYTES)), *order).sortWithinPartitions(*order, "text")

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary, True)
        part, seq, held = TaskContext.get().partitionId(), 0, 0
        names: list[pa.Array] = []
        ids: list[np.ndarray] = []
        sizes: list[np.ndarray] = []

        def block() -> pa.RecordBatch:
            array, size = np.concatenate(ids), np.concatenate(sizes)
            known = pa.chunked_array(names)
            missing = known.null_count
            own = known.drop_null().to_numpy()
            low = int(own[0] if len(own) else 0) - (missing > 0)
            shifted = np.r_[np.zeros(missing, np.uint64), own.view(np.uint64) - np.array([low], np.int64).view(np.uint64)]  # nulls sort first
            bounds = np.r_[0, np.cumsum(size)]
            return pa.record_batch({
                "part": pa.array([part], pa.int32()), "seq": pa.array([seq], pa.int32()), "first_doc": pa.array([low], pa.int64()), "n_docs": pa.array([len(size)], pa.int64()), "n_ids": pa.array([len(array)], pa.int64()),
                "width": pa.array([array.itemsize], pa.int32()), "doc_ids": pa.array([EliasFano.encode(shifted).to_bytes()], pa.binary()), "bounds": pa.array([EliasFano.encode(bounds).to_bytes()], pa.binary()), "ids": pa.array([array.tobytes()], pa.binary()),
            })

        for batch in batches:
            for piece in slices(batch):
                counts, own = encode(piece.column("text"))
                with_end = np.full(len(own) + len(counts), end_id, encode.kind)
                with_end[np.arange(len(own)) + np.repeat(np.arange(len(counts)), counts)] = own
                names.append(piece.column("doc_id"))
                ids.append(with_end)
                sizes.append(counts + 1)
                held += len(with_end)
                if held >= BLOCK_IDS:
                    yield block()
                    names, ids, sizes, held, seq = [], [], [], 0, seq + 1
        if names:
            yield block()

    ordered.mapInArrow(tidy(blocks), BLOCK_SCHEMA).write.mode("overwrite").parquet(path)


def _placed(spark: SparkSession, path: str) -> DataFrame:
    """The stored blocks, each with the number of ids in all blocks before it."""
    stored = spark.read.schema(BLOCK_SCHEMA).parquet(path)
    # Running sums in three steps, so that no window holds more than a run: runs of parts, parts of a run, blocks of a part.
    inside = stored.select("part", "seq", "n_ids").withColumn("run", F.shiftright("part", 12))
    runs = inside.groupBy("run").agg(F.sum("n_ids").alias("n")).withColumn("run_start", F.sum("n").over(Window.orderBy("run")) - F.col("n")).drop("n")
    parts = inside.groupBy("run", "part").agg(F.sum("n_ids").alias("n")).withColumn("part_start", F.sum("n").over(Window.partitionBy("run").orderBy("part")) - F.col("n")).drop("n")
    starts = inside.join(runs, "run").join(parts, ["run", "part"]).withColumn("before", F.sum("n_ids").over(Window.partitionBy("part").orderBy("seq")) - F.col("n_ids"))
    starts = Scratch(spark).keep(starts.select("part", "seq", (F.col("before") + F.col("part_start") + F.col("run_start")).alias("block_start")), "starts")
    return stored.join(narrow(starts), ["part", "seq"])


def _documents(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, bytes]:
    """(doc_ids, starts, bounds, ids as little-endian uint32 bytes) of a block."""
    names = EliasFano.from_bytes(row["doc_ids"]).values() + row["first_doc"]
    bounds = EliasFano.from_bytes(row["bounds"]).values()
    ids = np.frombuffer(row["ids"], "<u4" if row["width"] == 4 else "<u2").astype("<u4")
    return names, bounds[:-1] + row["block_start"], bounds, ids.tobytes()


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids (binary, little-endian uint32) of every document, from the files alone."""

    def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                names, starts, bounds, raw = _documents(row)
                for k in range(0, len(names), 1024):
                    cut = bounds[k : k + 1025]
                    yield pa.record_batch({
                        "doc_id": pa.array(names[k : k + 1024], pa.int64()), "start": pa.array(starts[k : k + 1024], pa.int64()), "n_tokens": pa.array(np.diff(cut), pa.int64()),
                        "ids": pa.array([raw[4 * a : 4 * b] for a, b in zip(cut[:-1], cut[1:], strict=True)], pa.binary()),
                    })

    return _placed(spark, path).mapInArrow(tidy(unpacked), "doc_id long, start long, n_tokens long, ids binary")


def read_documents(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """doc_id, n_tokens, ids (binary, little-endian uint32) of the given documents, found by select inside the blocks.

    A document that several rows share gives a row each; ids that aren't stored give none.
    """
    wanted = sorted({int(x) for x in doc_ids})

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                names, bounds = EliasFano.from_bytes(row["doc_ids"]), EliasFano.from_bytes(row["bounds"])
                out = []
                for name in wanted:
                    k = names.place_of(name - row["first_doc"]) if name >= row["first_doc"] else names.n
                    while k < names.n and names.select(k) + row["first_doc"] == name:
                        a, b, kind = bounds.select(k), bounds.select(k + 1), f"<u{row['width']}"
                        out.append((name, b - a, np.frombuffer(row["ids"], kind, b - a, a * row["width"]).astype("<u4").tobytes()))
                        k += 1
                yield pa.record_batch([pa.array([x[k] for x in out], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.binary()))], names=["doc_id", "n_tokens", "ids"])

    stored = spark.read.schema(BLOCK_SCHEMA).parquet(path).where(F.col("first_doc") <= max(wanted, default=-(2**63)))
    return stored.select("first_doc", "width", "doc_ids", "bounds", "ids").mapInArrow(found, "doc_id long, n_tokens long, ids binary")


def token_file_digests(docs: DataFrame, path: str | None = None, vocabulary: str = VOCABULARY) -> DataFrame:
    """Writes the files, reads them back, and returns doc_id, start, n_tokens, ids_crc32 of each document."""
    spark = docs.sparkSession
    path = path or Scratch(spark).path("token-files")
    write_token_files(docs, path, vocabulary)

    def digested(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                names, starts, bounds, raw = _documents(row)
                view = memoryview(raw)
                crc = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                yield pa.record_batch({"doc_id": pa.array(names, pa.int64()), "start": pa.array(starts, pa.int64()), "n_tokens": pa.array(np.diff(bounds), pa.int64()), "ids_crc32": pa.array(crc, pa.int64())})

    return _placed(spark, path).mapInArrow(tidy(digested), "doc_id long, start long, n_tokens long, ids_crc32 long")
