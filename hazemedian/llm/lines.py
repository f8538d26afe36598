"""Fuzzy line dedup by MinHash: one line of every group of near-equal lines stays.

A line's set holds its 8-character shingles (A-Z lower-cased, outer blanks off).  One hash of each shingle
serves all positions of the signature: its high part chooses one of the signature's bins, which keeps the smallest
hash; empty bins borrow from a fixed sequence of other bins.  Twelve bands of three bins meet at
Jaccard 0.75 with a chance of 0.998 (1 - (1 - 0.75^3)^12).

Lines that share a band key come to one task with their texts, so that pairs never become rows.  The task tests pairs of a
key by the exact Jaccard of their sets, at 0.75, from the most alike signatures down, leaves out pairs that
are joined already and pairs whose signatures agree in fewer than half of the bins (a chance of 0.001 at 0.75), and
gives the links that join them.  A pair that shares several keys is tested at its first band alone.  A key of more than
KEY_LINES lines goes to star rounds and a round of what still crosses instead (`link_nodes`).  A distributed
union-find over all links keeps the first line of each component.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import GROUP_BYTES, group_of, pack, shared_keys, sorted_runs
from .common import LOWER, ROW_KEY, WORD_CODE, Scratch, free_name, keyed, mix, narrow, slices, span_hashes, text_buffer, tidy, word_spans
from .components import connected, link_nodes
from .jaccard import SHARE, WHOLE

WIDTH = 8
BANDS, BAND_BINS = 12, 3
BINS = BANDS * BAND_BINS
#: Lines of a key whose pairs one task tests, bytes of lines of such a task.
KEY_LINES = 4096
TASK_BYTES = 2 << 20
_BORROW = np.random.Generator(np.random.PCG64(77)).integers(0, BINS, (64, BINS))
_NEWLINE = np.zeros(256, bool)
_NEWLINE[10] = True
_BLANK = np.zeros(256, bool)
_BLANK[[9, 11, 12, 13, 32]] = True


def line_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, row, line number in its row) of the lines that hold a visible character, blanks cut off."""
    starts, ends, rows = word_spans(data, offsets, ~_NEWLINE)
    if not len(starts):
        return starts, ends, rows, rows
    before = np.zeros(len(data) + 1, np.int64)
    np.cumsum(_NEWLINE[data], out=before[1:])
    number = before[starts] - before[offsets[rows]]
    seen = np.flatnonzero(~_BLANK[data] & ~_NEWLINE[data])
    lo, hi = np.searchsorted(seen, starts), np.searchsorted(seen, ends)
    full = hi > lo
    return seen[lo[full]], seen[hi[full] - 1] + 1, rows[full], number[full]


def line_shingles(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit code of a shingle, line) in order of place; a shorter line is its only shingle.

    The code of eight characters below 256 is their bytes; greater ones add a hash of what is above their low byte.
    """
    before = np.zeros(len(data) + 1, np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=before[1:])
    starts, ends = before[starts], before[ends]
    if before[-1] == len(data):
        low, high = data, None
    else:
        points = np.frombuffer(data.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32)
        low, high = points.astype(np.uint8), points >> 8
        high = high * np.uint64(0x9E3779B97F4A7C15) if high.any() else None
    codes = np.ndarray(len(low), "<u8", np.r_[low, np.zeros(8, np.uint8)].data, strides=(1,))
    size = ends - starts
    count = np.maximum(size - WIDTH + 1, 1)
    first = np.cumsum(count) - count
    line = np.repeat(np.arange(len(starts)), count)
    at = np.arange(len(line)) + np.repeat(starts - first, count)
    out = codes[at]
    short = np.flatnonzero(size < WIDTH)
    n = size[short].astype(np.uint64)
    out[first[short]] = (out[first[short]] & (np.uint64(1) << n * np.uint64(8)) - np.uint64(1)) + n * WORD_CODE[0]
    if high is not None:
        high = np.r_[high, np.zeros(WIDTH, np.uint64)]
        for k in range(WIDTH):
            inside = np.ones(len(at), bool)
            inside[first[short]] = size[short] > k
            out += np.where(inside, high[at + k] * WORD_CODE[k + 1], np.uint64(0))
    return out, line


def line_sets(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ascending shingle codes of each line without repeats, first places of the lines)."""
    codes, line = line_shingles(data, starts, ends)
    bounds = np.searchsorted(line, np.arange(len(starts) + 1))
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        codes[a:b].sort()
    keep = sorted_runs(line, codes)
    return codes[keep], np.searchsorted(line[keep], np.arange(len(starts) + 1))


def signatures(codes: np.ndarray, lines: np.ndarray, n: int) -> np.ndarray:
    """n rows of BINS minima, every bin filled; repeats of a shingle change nothing."""
    empty = np.uint64(2**64 - 1)
    out = np.full(n * BINS, empty, np.uint64)
    hashes = (codes ^ codes >> np.uint64(32)) * np.uint64(0x9E3779B97F4A7C15)
    hashes ^= hashes >> np.uint64(29)
    hashes *= np.uint64(0xBF58476D1CE4E5B9)
    bins = ((hashes >> np.uint64(32)) * np.uint64(BINS) >> np.uint64(32)).astype(np.int64)
    bins += lines * BINS
    np.minimum.at(out, bins, hashes)
    out = out.reshape(n, BINS)
    filled = out != empty
    for turn in _BORROW:
        need = ~filled & ~(out != empty)
        if not need.any():
            break
        out = np.where(need & filled[:, turn], mix(out[:, turn] + np.uint64(1)), out)
    return out


def band_keys(signature: np.ndarray) -> np.ndarray:
    keys = np.zeros((len(signature), BANDS), np.uint64)
    for k in range(BAND_BINS):
        keys = mix(keys * np.uint64(3) + signature[:, k::BAND_BINS])
    return mix(keys + np.arange(BANDS, dtype=np.uint64)[None, :])


def line_ids(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return span_hashes(data, starts, ends).view(np.int64)


def _lines(part: pa.RecordBatch):
    data, offsets = text_buffer(part.column("text"))
    data = LOWER[data]
    starts, ends, rows, number = line_spans(data, offsets)
    return data, starts, ends, rows, number, line_ids(data, starts, ends)


def alike(x: np.ndarray, y: np.ndarray) -> bool:
    """Whether two ascending sets have a Jaccard similarity of 0.75 or more."""
    if WHOLE * min(len(x), len(y)) < SHARE * max(len(x), len(y)):
        return False
    merged = np.concatenate((x, y))
    merged.sort()
    both = int((merged[1:] == merged[:-1]).sum())
    return WHOLE * both >= SHARE * (len(merged) - both)


class _Lines:
    """Different lines of a task: their sets, band keys and signatures."""

    def __init__(self, items: list[bytes]):
        data, ends = np.frombuffer(b"".join(items), np.uint8), np.cumsum([len(x) for x in items])
        codes, bounds = line_sets(data, np.r_[0, ends[:-1]], ends)
        self.sets = [codes[a:b] for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
        signature = signatures(codes, np.repeat(np.arange(len(items)), np.diff(bounds)), len(items))
        self.keys, self.signature = band_keys(signature).view(np.int64), signature.astype(np.uint16)


def _pairs_of_keys(lines: _Lines, keys: np.ndarray, places: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(left, right, agreeing bins) of pairs of lines that share a key, at the first band they share; keys lie in order."""
    first = sorted_runs(keys)
    count = np.diff(np.r_[first, len(keys)])
    left, right, held = [], [], 0

    def met() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        at, a, b = (np.concatenate(x) for x in (of, left, right))
        same = lines.keys[a] == lines.keys[b]
        band = (lines.keys[a] == at[:, None]).argmax(1)
        agree = (lines.signature[a] == lines.signature[b]).sum(1)
        keep = (same.argmax(1) == band) & (2 * agree >= BINS)
        return a[keep], b[keep], agree[keep]

    of: list[np.ndarray] = []
    for start, n in zip(first.tolist(), count.tolist(), strict=True):
        own = places[start : start + n]
        step = max(1, (1 << 16) // n)
        for k in range(0, n - 1, step):
            rows = np.arange(k, min(k + step, n - 1))
            a = np.repeat(rows, n - 1 - rows)
            b = a + 1 + np.arange(len(a)) - np.repeat(np.cumsum(n - 1 - rows) - (n - 1 - rows), n - 1 - rows)
            left.append(own[a])
            right.append(own[b])
            of.append(np.full(len(a), keys[start]))
            held += len(a)
            if held >= 1 << 16:
                yield met()
                left, right, of, held = [], [], [], 0
    if held:
        yield met()


def key_links(table: pa.Table) -> pa.Table:
    """The links (a, b) that join the lines of a task's keys (key, node, items)."""
    order = np.lexsort((table.column("node").to_numpy(), table.column("key").to_numpy()))
    table = table.take(pa.array(order))
    nodes, at, place = np.unique(table.column("node").to_numpy(), return_index=True, return_inverse=True)
    lines = _Lines(table.column("items").take(pa.array(at)).to_pylist())
    top = list(range(len(nodes)))

    def root(x: int) -> int:
        while top[x] != x:
            top[x] = top[top[x]]
            x = top[x]
        return x

    found: list[tuple[int, int]] = []
    for left, right, agree in _pairs_of_keys(lines, table.column("key").to_numpy(), place):
        turn = np.argsort(-agree, kind="stable")
        for a, b in zip(left[turn].tolist(), right[turn].tolist(), strict=True):
            x, y = root(a), root(b)
            if x != y and alike(lines.sets[a], lines.sets[b]):
                top[max(x, y)] = min(x, y)
                found.append((a, b))
    ends = np.array(found, np.int64).reshape(-1, 2)
    return pa.table({"a": pa.array(nodes[ends[:, 0]]), "b": pa.array(nodes[ends[:, 1]])})


def verified_lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The pairs (a, b) whose lines (left, right) have sets of Jaccard 0.75 or more."""
    for batch in batches:
        for at in range(0, batch.num_rows, 4096):
            part = batch.slice(at, 4096)
            names, first, place = np.unique(np.r_[part.column("a").to_numpy(), part.column("b").to_numpy()], return_index=True, return_inverse=True)
            items = [*part.column("left").to_pylist(), *part.column("right").to_pylist()]
            sets = _Lines([items[k] for k in first.tolist()]).sets
            keep = [alike(sets[x], sets[y]) for x, y in zip(place[: part.num_rows].tolist(), place[part.num_rows :].tolist(), strict=True)]
            yield part.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))


def _occurrences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every line; `row` tells rows of one doc_id apart, by task and place."""
    seen = TaskContext.get().partitionId() << 33
    for batch in batches:
        for part in slices(batch):
            _, starts, _, rows, number, ids = _lines(part)
            seen += part.num_rows
            if len(starts):
                yield pa.record_batch({"doc_id": part.column("doc_id").take(pa.array(rows)), "row": pa.array(seen - part.num_rows + rows, pa.int64()), "line_no": pa.array(number, pa.int64()), "node": pa.array(ids)})


def _first_of_each(ids: np.ndarray) -> np.ndarray:
    return np.sort(np.unique(ids, return_index=True)[1])


def line_components(docs: DataFrame) -> DataFrame:
    """Every line that has an equal or near-equal one: doc_id, line_no (from 0, as the text is cut at newlines),
    keep_doc_id, keep_line_no (the first line of its component by doc_id, row and line number), kept boolean.

    Lines that stand alone give no row.  Null, empty and blank lines are no lines; repeated rows and rows that share a doc_id
    are rows like others, of which only the first keeps its lines; rows with a null doc_id are left out; a very long line is a line like others; an empty table gives
    no row; other columns are not read.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id is not null")
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    # A line of 100 bytes gives BANDS elements.
    groups = max(1, int(total // 100 * BANDS * 24 // GROUP_BYTES))

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts():
            for batch in batches:
                for part in slices(batch):
                    data, starts, ends, _, _, ids = _lines(part)
                    if not len(starts):
                        continue
                    once = _first_of_each(ids)
                    keys = band_keys(signatures(*line_shingles(data, starts[once], ends[once]), len(once))).ravel().view(np.int64)
                    yield group_of(keys, groups), np.repeat(ids[once], BANDS), np.zeros(len(keys), np.int32), keys

        yield from pack(parts())

    postings = scratch.keep(shared_keys(rows.mapInArrow(tidy(blocks), "g long, block binary")), "postings")
    occurrences = scratch.keep(rows.mapInArrow(tidy(_occurrences), "doc_id long, row long, line_no long, node long"), "lines")
    firsts = scratch.keep(occurrences.groupBy("node").agg(F.min(F.struct("doc_id", "row", "line_no")).alias("first"), F.count("*").alias("times")), "firsts")
    wanted = scratch.keep(firsts.join(postings.select("node").distinct(), "node", "left_semi").select("node", "first.doc_id"), "wanted")

    def as_lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                data, starts, ends, _, _, ids = _lines(part)
                once, raw = _first_of_each(ids), data.tobytes()
                yield pa.record_batch({"node": pa.array(ids[once], pa.int64()), "items": pa.array([raw[a:b] for a, b in zip(starts[once].tolist(), ends[once].tolist(), strict=True)], pa.binary())})

    few = rows.join(narrow(wanted.select("doc_id").distinct()), "doc_id", "left_semi")
    texts = few.mapInArrow(tidy(as_lines), "node long, items binary").join(narrow(wanted.select("node")), "node", "left_semi")
    texts = scratch.keep(texts.dropDuplicates(["node"]), "texts")

    often = scratch.keep(postings.groupBy("key").agg(F.count("*").alias("c")).where(F.col("c") > KEY_LINES).select("key"), "often")
    met = postings.join(narrow(often), "key", "left_anti").select("key", "node").join(texts, "node")
    size = postings.join(texts.select("node", F.octet_length("items").alias("size")), "node").agg(F.sum(F.col("size") + 64)).first()[0] or 0
    bucket = F.pmod(F.xxhash64("key"), F.lit(max(1, int(size // TASK_BYTES))))
    links = scratch.keep(met.withColumn("bucket", bucket).groupBy("bucket").applyInArrow(tidy(key_links), "a long, b long"), "links")
    if not often.isEmpty():

        def verify(pairs: DataFrame) -> DataFrame:
            left, right = (texts.select(F.col("node").alias(k), F.col("items").alias(name)) for k, name in (("a", "left"), ("b", "right")))
            both = pairs.join(left, "a").join(right, "b").select("a", "b", "left", "right")
            return scratch.keep(both.mapInArrow(verified_lines, "a long, b long"), "linked")

        hot = scratch.keep(postings.join(narrow(often), "key").withColumn("pos", F.lit(0)), "hot")
        links = links.union(link_nodes(scratch, hot, lambda *_: F.lit(True), verify).select(F.col("node").alias("a"), F.col("label").alias("b")))
    labels = scratch.keep(connected(scratch, links), "labels")
    scratch.drop(postings, texts)
    named = firsts.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    groups_ = named.groupBy("label").agg(F.min("first").alias("keep"), F.sum("times").alias("times")).where("times > 1")
    of = scratch.keep(named.join(groups_.select("label", "keep"), "label").select("node", "keep"), "of")
    found = occurrences.join(of, "node")
    return found.select("doc_id", "line_no", F.col("keep.doc_id").alias("keep_doc_id"), F.col("keep.line_no").alias("keep_line_no"), (F.struct("doc_id", "row", "line_no") == F.col("keep")).alias("kept"))


def without_repeated_lines(docs: DataFrame) -> DataFrame:
    """`docs` with every line removed that another kept line stands for, the first one in the order of the rows.

    Rows are told apart by a row_key, so that null and repeated doc_ids are rows like others and a row loses its own lines
    only; null texts stay null, blank lines stay; empty tables stay empty; all columns stay, whatever their names.
    """
    rows = keyed(docs)
    name = free_name(rows, "gone")
    gone = line_components(rows.select(F.col(ROW_KEY).alias("doc_id"), "text")).where("not kept").groupBy(F.col("doc_id").alias(ROW_KEY)).agg(F.collect_set("line_no").alias(name))
    kept = F.filter(F.split("text", "\n"), lambda line, k: ~F.array_contains(F.coalesce(F.col(name), F.array().cast("array<bigint>")), k.cast("long")))
    return rows.join(gone, ROW_KEY, "left").withColumn("text", F.array_join(kept, "\n")).select(docs.columns)
