"""Benchmark decontamination by greedy string tiling.

Documents and benchmark items are sequences of tokens (runs of letters and digits, A-Z lower-cased).  Karp-Rabin
window hashes of MATCH tokens at every place are the seeds; a document meets an item where seeds are equal.  For each such
pair the longest common run of unmarked tokens is marked in both again and again, until none of at least MATCH
tokens is left.  Tiles may lie in any order, so reordered passages count in full.  An item whose tiled share
reaches COVERAGE makes the document contaminated.

The benchmark goes to the tasks in blocks of at most BLOCK_BYTES of text; documents are read once a block and never
shuffled.  Coverage belongs to a (document, item) pair, so blocks change nothing in the result.
"""

from __future__ import annotations

from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, WORD_BYTE, mix, slices, span_hashes, text_buffer, tidy, word_spans

MATCH = 5
COVERAGE = 0.5
BLOCK_BYTES = 16 << 20
#: Seeds that are looked at together.
SEEDS = 1 << 19
_RADIX = np.uint64(0xB492B66FBE98F273)


def tokens_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(token hash, row) of a string column."""
    data, offsets = text_buffer(column)
    data = LOWER[data]
    starts, ends, rows = word_spans(data, offsets, WORD_BYTE)
    return span_hashes(data, starts, ends), rows


def windows(tokens: np.ndarray, rows: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(start, Karp-Rabin hash) of the windows of `width` tokens inside a row."""
    n = len(tokens) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    for k in range(width):
        total = total * _RADIX + tokens[k : k + n]
    inside = np.flatnonzero(rows[:n] == rows[width - 1 :])
    return inside, mix(total[inside])


def tiles(doc: np.ndarray, item: np.ndarray, at_doc: np.ndarray, at_item: np.ndarray, match: int) -> list[tuple[int, int, int]]:
    """Greedy tiles (length, place in item, place in document) from the seeds of two token arrays."""
    # A seed whose tokens before are equal too belongs to the run of an earlier one.
    before = (at_doc > 0) & (at_item > 0)
    before &= doc[np.maximum(at_doc - 1, 0)] == item[np.maximum(at_item - 1, 0)]
    at_doc, at_item = at_doc[~before], at_item[~before]
    length, live = np.zeros(len(at_doc), np.int64), np.arange(len(at_doc))
    while len(live):  # equal hashes are checked token by token, and runs extended
        i, j = at_doc[live] + length[live], at_item[live] + length[live]
        live = live[(i < len(doc)) & (j < len(item))]
        i, j = at_doc[live] + length[live], at_item[live] + length[live]
        live = live[doc[i] == item[j]]
        length[live] += 1
    heap = [(-n, t, d) for n, t, d in zip(length.tolist(), at_item.tolist(), at_doc.tolist(), strict=True) if n >= match]
    heapify(heap)
    free_doc, free_item, out = np.ones(len(doc), bool), np.ones(len(item), bool), []
    while heap:
        n, j, i = heappop(heap)
        n = -n
        free = free_doc[i : i + n] & free_item[j : j + n]
        if free.all():
            free_doc[i : i + n] = free_item[j : j + n] = False
            out.append((n, j, i))
            continue
        if free_item.sum() < match:
            break
        edges = np.flatnonzero(np.diff(np.r_[False, free, False].astype(np.int8)))
        for a, b in zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True):
            if b - a >= match:
                heappush(heap, (a - b, j + a, i + a))
    return out


class Items:
    """A block of the benchmark: its tokens, and its seeds by width, ascending by hash."""

    def __init__(self, ids: list[int], texts: list[str], match: int):
        tokens, rows = tokens_of(pa.array(texts, pa.string()))
        self.ids, self.match = ids, match
        counts = np.bincount(rows, minlength=len(ids))
        bounds = np.r_[0, np.cumsum(counts)]
        self.whole, self.starts = tokens, bounds[:-1]
        self.tokens = [tokens[a:b] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        self.seeds = {}
        for width in range(1, match + 1):  # an item of fewer tokens is its own seed
            fit = np.flatnonzero(counts >= match if width == match else counts == width)
            keep = np.isin(rows, fit)
            at, h = windows(tokens[keep], rows[keep], width)
            if len(at):
                order = np.argsort(h, kind="stable")
                own = rows[keep][at]
                self.seeds[width] = h[order], own[order], (np.flatnonzero(keep)[at] - bounds[own])[order]

    def pairs(self, column: pa.Array) -> Iterator[tuple[int, int, int, int, int, float]]:
        """(row, item, tiles, tiled tokens, longest tile, tiled share) of every pair that shares a seed."""
        tokens, rows = tokens_of(column)
        first = np.searchsorted(rows, np.arange(len(column) + 1))
        for width, (hashes, items, places) in self.seeds.items():
            at, h = windows(tokens, rows, width)
            lo, hi = np.searchsorted(hashes, h), np.searchsorted(hashes, h, side="right")
            n = hi - lo
            if not n.any():
                continue
            met: list = []
            ends = np.cumsum(n)
            first_at = 0
            while first_at < len(at):  # at most SEEDS at a time, of which only the first of a run of equal tokens stay
                last_at = max(first_at + 1, int(np.searchsorted(ends, ends[first_at] - n[first_at] + SEEDS, side="right")))
                some = n[first_at:last_at]
                doc_at = np.repeat(at[first_at:last_at], some)
                seed = np.arange(int(some.sum())) - np.repeat(np.cumsum(some) - some, some) + np.repeat(lo[first_at:last_at], some)
                item, place = items[seed], places[seed]
                before = (place > 0) & (doc_at > first[rows[doc_at]])
                before &= self.whole[np.maximum(self.starts[item] + place - 1, 0)] == tokens[np.maximum(doc_at - 1, 0)]
                met.append((rows[doc_at][~before], item[~before], doc_at[~before], place[~before]))
                first_at = last_at
            row, item, doc_at, place = (np.concatenate(x) for x in zip(*met, strict=True))
            order = np.lexsort((item, row))
            row, item, doc_at, place = row[order], item[order], doc_at[order], place[order]
            cut = np.flatnonzero(np.r_[True, (np.diff(row) != 0) | (np.diff(item) != 0)])
            for a, b in zip(cut.tolist(), np.r_[cut[1:], len(row)].tolist(), strict=True):
                r, t = int(row[a]), int(item[a])
                own = self.tokens[t]
                found = tiles(tokens[first[r] : first[r + 1]], own, doc_at[a:b] - first[r], place[a:b], width)
                if found:
                    tiled = sum(x[0] for x in found)
                    yield r, self.ids[t], len(found), tiled, max(x[0] for x in found), tiled / len(own)


def _blocks(benchmark: DataFrame) -> Iterator[list]:
    """The items in runs of ascending ids of at most BLOCK_BYTES; sizes are read first, texts a block at a time."""
    rows = benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).where("item_id is not null and text is not null")
    low, total, high = rows.agg(F.min("item_id"), F.sum(F.octet_length("text") + 16), F.max("item_id")).first()
    if low is None:
        return
    if total <= BLOCK_BYTES:
        yield rows.collect()
        return
    waiting = [(low, high)]
    while waiting:
        a, b = waiting.pop()
        part = rows.where(F.col("item_id").between(a, b))
        size = part.agg(F.sum(F.octet_length("text") + 16)).first()[0]
        if size is None:
            continue
        if size <= BLOCK_BYTES:
            yield part.collect()
        elif a < b:
            waiting += [((a + b) // 2 + 1, b), (a, (a + b) // 2)]
        else:  # many rows of one id
            pieces = 2 * -(-size // BLOCK_BYTES)
            for k in range(pieces):
                yield part.where(F.pmod(F.xxhash64("text"), F.lit(pieces)) == k).distinct().collect()


def contaminated_pairs(docs: DataFrame, benchmark: DataFrame, match: int = MATCH, coverage: float = COVERAGE) -> DataFrame:
    """doc_id, item_id, n_tiles, tiled_tokens, longest_tile, coverage of every pair with coverage >= `coverage`.

    Null and empty texts on either side meet nothing; an item of fewer than `match` tokens must occur whole;
    of equally long runs the first in the item, then in the document is marked first; a very long text is one slice, and its
    seeds are looked at SEEDS at a time; rows with a null doc_id or item_id are left out; repeated rows each give a
    row; empty tables give no row; other columns are not read.
    """
    spark = docs.sparkSession
    schema = "doc_id long, item_id long, n_tiles int, tiled_tokens int, longest_tile int, coverage double"
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("doc_id is not null")
    out = None
    for block in _blocks(benchmark):
        sent = spark.sparkContext.broadcast(([x["item_id"] for x in block], [x["text"] for x in block]))

        def met(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            items = Items(*sent.value, match)
            for batch in batches:
                for part in slices(batch):
                    found = [x for x in items.pairs(part.column("text")) if x[-1] >= coverage]
                    names = part.column("doc_id").take(pa.array([x[0] for x in found], pa.int64()))
                    kinds = pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64()
                    yield pa.record_batch([names, *(pa.array([x[k + 1] for x in found], kind) for k, kind in enumerate(kinds))], names=["doc_id", "item_id", "n_tiles", "tiled_tokens", "longest_tile", "coverage"])

        one = rows.mapInArrow(tidy(met), schema)
        out = one if out is None else out.union(one)
    return spark.createDataFrame([], schema) if out is None else out
