"""What the corpus operators share: shared storage, slicing of Arrow batches, vectorised word hashing.

Texts are handled as UTF-8 bytes.  One Arrow batch is cut into slices of bounded bytes, and a slice is
processed as one numpy buffer, so that no operator holds more than a slice of intermediate arrays.
"""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import suppress
from functools import wraps
from inspect import isgeneratorfunction
from time import monotonic

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only up to this many rows of one or two numbers; beyond it a shuffled join is used.
BROADCAST_ROWS = 2_000_000
SLICE_BYTES = 1 << 19
#: Time between two clean-ups of shuffle files that no plan needs.
RELEASE_SECONDS = 8


def shared_root(spark: SparkSession) -> str:
    """The folder that all executors share; a folder of our own only in local mode (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        set_dir = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = set_dir.get() if set_dir.isDefined() else None
    if not root:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="hazemedian-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


class Scratch:
    """Tables written to the shared folder, which cut lineage and survive lost executors."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.root = f"{shared_root(spark)}/hazemedian-{uuid.uuid4().hex}"
        self.made, self.cleaned = 0, 0.0

    def path(self, label: str) -> str:
        self.made += 1
        return f"{self.root}/{self.made:03d}-{label}"

    def keep(self, df: DataFrame, label: str) -> DataFrame:
        self.release()
        path = self.path(label)
        df.write.mode("overwrite").parquet(path)
        kept = self.spark.read.schema(df.schema).parquet(path)
        kept.scratch_path = path
        return kept

    def release(self) -> None:
        """Lets Spark remove the shuffle files of steps whose plans nobody holds any more, now and then."""
        if monotonic() - self.cleaned < RELEASE_SECONDS:
            return
        self.cleaned = monotonic()
        gc.collect()
        self.spark._jvm.System.gc()

    def drop(self, *kept: DataFrame) -> None:
        """Deletes tables that no later step reads."""
        jvm = self.spark._jvm
        for df in kept:
            path = jvm.org.apache.hadoop.fs.Path(df.scratch_path)
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def trim() -> None:
    """Hands freed memory back to the system, which a worker's allocators would keep for its next task."""
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):  # an allocator without this call
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def tidy(f):
    """`f`, a function of a task or a generator of its batches, with `trim` at the end."""
    if isgeneratorfunction(f):

        @wraps(f)
        def run(batches):
            try:
                yield from f(batches)
            finally:
                trim()
    else:

        @wraps(f)
        def run(table):
            try:
                return f(table)
            finally:
                trim()

    return run


_held: dict = {}


def held_by_worker(key: tuple, make):
    """What `make` gives, held by the worker process for later tasks; another operator's tables leave for it."""
    if key not in _held:
        _held.clear()
        trim()
        _held[key] = make()
    return _held[key]


def narrow(small: DataFrame) -> DataFrame:
    """`small` with a broadcast hint if its counted rows are within the bound, else as it is."""
    return F.broadcast(small) if small.count() <= BROADCAST_ROWS else small


#: Names a row where doc_ids may be null or repeated.
ROW_KEY = "row_key"


def keyed(docs: DataFrame) -> DataFrame:
    """`docs` with a row_key, written to the shared folder if it has none yet."""
    return docs if ROW_KEY in docs.columns else Scratch(docs.sparkSession).keep(docs.withColumn(ROW_KEY, F.monotonically_increasing_id()), "keyed")


def free_name(df: DataFrame, wish: str) -> str:
    """A column name that `df` doesn't have in any case of letters."""
    held = {c.lower() for c in df.columns}
    while wish.lower() in held:
        wish += "_"
    return wish


def held_out(doc_id):
    """True for the fifth of the documents whose labels are never learnt from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def slices(batch: pa.RecordBatch, column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Runs of rows with about `most` text bytes at a time; a longer text makes a slice by itself."""
    lengths = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    ends, start, total = np.cumsum(lengths), 0, 0
    while start < batch.num_rows:
        stop = max(start + 1, int(np.searchsorted(ends, total + most, side="right")))
        yield batch.slice(start, stop - start)
        start, total = stop, int(ends[stop - 1])


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The concatenated UTF-8 bytes of a string column and the n+1 offsets of its rows; nulls are empty."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


_MIX = np.random.Generator(np.random.PCG64(20240607))
BYTE_CODE = _MIX.integers(1, 2**63, 256, dtype=np.uint64)
WORD_CODE = _MIX.integers(1, 2**63, 64, dtype=np.uint64) | np.uint64(1)
_BASE = 0x9E3779B97F4A7C15
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
#: Letters, digits and every byte of a non-ASCII character.
WORD_BYTE = np.zeros(256, bool)
WORD_BYTE[48:58] = WORD_BYTE[65:91] = WORD_BYTE[97:123] = WORD_BYTE[128:] = True


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        n = max(n, 2 * SLICE_BYTES)
        for k, base in enumerate((_BASE, _BASE_INVERSE)):
            steps = np.full(n, base, np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans, the same wherever a span stands."""
    up, down = _power_tables(len(data) + 1)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_CODE[data] * up[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def word_spans(data: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, row) of the maximal runs of bytes for which `inside`; runs never cross rows."""
    if not len(data):
        return (np.zeros(0, np.int64),) * 3
    flags = inside[data]
    before = np.empty_like(flags)
    before[0], before[1:] = False, flags[:-1]
    after = np.empty_like(flags)
    after[-1], after[:-1] = False, flags[1:]
    edges = offsets[1:-1]
    before[edges[edges < len(data)]] = False
    after[edges[edges > 0] - 1] = False
    starts = np.flatnonzero(flags & ~before)
    ends = np.flatnonzero(flags & ~after) + 1
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def shingle_hashes(words: np.ndarray, rows: np.ndarray, width: int, short: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row) of each run of `width` words; with `short`, a row of fewer words gives its whole run once."""
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    last = n - width + 1
    if last > 0:
        same = rows[:last] == rows[width - 1 :]
        total = np.zeros(last, np.uint64)
        for j in range(width):
            total += words[j : j + last] * WORD_CODE[j]
        found, of = mix(total + np.uint64(width))[same], rows[:last][same]
    else:
        found, of = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if short:
        first = np.flatnonzero(np.r_[True, rows[1:] != rows[:-1]])
        count = np.diff(np.r_[first, n])
        few = first[count < width], count[count < width]
        if len(few[0]):
            place = np.arange(n) - np.repeat(first, count)
            total = np.add.reduceat(words * WORD_CODE[np.minimum(place, 63)], first)
            whole = mix(total[count < width] + few[1].astype(np.uint64))
            found, of = np.r_[found, whole], np.r_[of, rows[few[0]]]
            order = np.argsort(of, kind="stable")
            found, of = found[order], of[order]
    return found, of


def row_sets(hashes: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row) without repeats inside a row, ascending by row and hash."""
    if not len(hashes):
        return hashes, rows
    order = np.lexsort((hashes, rows))
    hashes, rows = hashes[order], rows[order]
    new = np.r_[True, (hashes[1:] != hashes[:-1]) | (rows[1:] != rows[:-1])]
    return hashes[new], rows[new]
