"""Keys that several nodes share, found with packed blocks instead of rows.

Map tasks pack the elements (key, node) of bounded flushes into one binary block for each key group, so that a shuffle
moves bytes instead of rows.  A group's task sorts its elements and lets only keys pass that at least two different
nodes have.  The number of groups follows the data.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import tidy

GROUP_BYTES = 8 << 20
#: Elements that a map task holds before it packs them.
FLUSH_ELEMENTS = 1 << 19
#: Elements of one node beside each other in a block: the node, the size of its set, and how many follow.
RUN = np.dtype([("node", "<i8"), ("n", "<i4"), ("count", "<i4")])


def sorted_runs(*columns: np.ndarray) -> np.ndarray:
    """First places of the runs of equal rows of columns that lie in order."""
    if not len(columns[0]):
        return np.zeros(0, np.int64)
    new = np.ones(len(columns[0]), bool)
    new[1:] = np.logical_or.reduce([x[1:] != x[:-1] for x in columns])
    return np.flatnonzero(new)


def packed(groups: np.ndarray, nodes: np.ndarray, sizes: np.ndarray, *values: np.ndarray) -> Iterator[pa.RecordBatch]:
    """One block (g, block) for each group: number of runs, RUNs, then each array of values."""
    if not len(groups):
        return
    order = np.argsort(groups, kind="stable")
    groups, nodes, sizes = groups[order], nodes[order], sizes[order]
    values = tuple(x[order] for x in values)
    first = sorted_runs(groups, nodes)
    runs = np.empty(len(first), RUN)
    runs["node"], runs["n"], runs["count"] = nodes[first], sizes[first], np.diff(np.r_[first, len(nodes)])
    cut = sorted_runs(groups)
    ends, run_cut = np.r_[cut[1:], len(groups)], np.searchsorted(first, np.r_[cut, len(groups)])
    blocks = [np.int64(d - c).tobytes() + runs[c:d].tobytes() + b"".join(x[a:b].tobytes() for x in values) for a, b, c, d in zip(cut.tolist(), ends.tolist(), run_cut[:-1].tolist(), run_cut[1:].tolist(), strict=True)]
    for k in range(0, len(cut), 512):
        yield pa.record_batch({"g": pa.array(groups[cut[k : k + 512]], pa.int64()), "block": pa.array(blocks[k : k + 512], pa.binary())})


def pack(parts: Iterator[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
    """Blocks of a task's (groups, nodes, sizes, values ...), some FLUSH_ELEMENTS at a time."""
    held: list = []
    size = 0
    for part in parts:
        held.append(part)
        size += len(part[0])
        if size >= FLUSH_ELEMENTS:
            yield from packed(*(np.concatenate(x) for x in zip(*held, strict=True)))
            held, size = [], 0
    if size:
        yield from packed(*(np.concatenate(x) for x in zip(*held, strict=True)))


def unpacked(blocks: pa.ChunkedArray, *kinds: str, once: bool = False) -> list[np.ndarray]:
    """[runs, values ...] of the elements of blocks, in their order.

    With `once` only the first run of each node stays: in a key group all runs of a node hold the same elements.
    """
    heads, parts = [np.zeros(0, RUN)], [[] for _ in kinds]
    for chunk in blocks.chunks:
        for x in chunk:
            raw = x.as_buffer()
            runs = np.frombuffer(raw, RUN, int(np.frombuffer(raw, np.int64, 1)[0]), 8)
            heads.append(runs)
            at, count = 8 + runs.nbytes, int(runs["count"].sum())
            for k, kind in enumerate(kinds):
                parts[k].append(np.frombuffer(raw, kind, count, at))
                at += parts[k][-1].nbytes
    runs = np.concatenate(heads)
    if not once:
        return [runs, *(np.concatenate([np.zeros(0, k), *x]) for k, x in zip(kinds, parts, strict=True))]
    keep = np.zeros(len(runs), bool)
    keep[np.unique(runs["node"], return_index=True)[1]] = True
    ends, values = np.cumsum([len(x) for x in heads]), [[np.zeros(0, k)] for k in kinds]
    for j in range(1, len(heads)):
        own = keep[ends[j - 1] : ends[j]]
        mask = None if own.all() else np.repeat(own, heads[j]["count"])
        for k, x in enumerate(parts):
            values[k].append(x[j - 1] if mask is None else x[j - 1][mask])
    return [runs[keep], *map(np.concatenate, values)]


def shared_places(runs: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(places, runs, nodes of the key) of the elements whose key at least two runs have, in order of key; each node has one run."""
    order = np.argsort(keys, kind="stable")
    first = sorted_runs(keys[order])
    count = np.diff(np.r_[first, len(order)])
    some = np.repeat(count > 1, count)
    order, count = order[some], np.repeat(count[count > 1], count[count > 1])
    of = np.repeat(np.arange(len(runs), dtype=np.int32), runs["count"])
    return order, of[order], count


def group_of(keys: np.ndarray, groups: int) -> np.ndarray:
    return ((keys.view(np.uint64) >> np.uint64(20)) % np.uint64(groups)).astype(np.int64)


def shared_keys(blocks: DataFrame) -> DataFrame:
    """(key, node, n) of the keys that at least two nodes have, each (key, node) once."""

    def shared(table: pa.Table) -> pa.Table:
        runs, keys = unpacked(table.column("block"), "<i8", once=True)
        keep, of, _ = shared_places(runs, keys)
        return pa.table({"key": pa.array(keys[keep]), "node": pa.array(np.ascontiguousarray(runs["node"][of])), "n": pa.array(np.ascontiguousarray(runs["n"][of]))})

    return blocks.groupBy("g").applyInArrow(tidy(shared), "key long, node long, n int")
