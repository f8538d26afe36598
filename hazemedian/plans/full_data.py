"""The whole-node solver on inputs beyond one task: every step is a scan of stored blocks of nodes, shared by all runs.

A run is a generator that asks for scans and gets their merged replies.  A scan answers the questions of all runs at once; a
task holds one block and, for each question, sums of the size of the centres.  Seeds come from races of hashes, so that they
don't depend on the partitions.
"""

from __future__ import annotations

import pickle
from collections.abc import Generator, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..model import PRACTICAL, Profile
from ..operators.medians import packed_batches
from ..sources.tables import BATCH_BYTES, kept, small_batches

#: Locations of a stored block, unless one node has more, and of a step of a scan.
BLOCK_PAIRS = 4096
#: Bytes of the row groups that stored blocks are read by.
GROUP_BYTES = 2 << 20
#: Candidates of a seeding scan for each seed that is taken from them.
POOL = 16
#: A step of this part of a group's extent is the last one.
SETTLED = 1e-9
#: Kinds of numbers that a coordinate may be stored as, where a whole block's are exactly so.
KINDS = ("<u1", "<f4", "<f8")
FIELDS = {"node_id": "<i8", "weight": "<f8", "counts": "<i8", "loc_id": "<i8", "prob": "<f8"}
STORED = {"compression": "zstd", "parquet.enable.dictionary": "false", "parquet.block.size": str(GROUP_BYTES), "parquet.block.size.row.check.min": "4", "parquet.block.size.row.check.max": "16", "parquet.page.size.row.check.min": "4"}


def _narrow(x: np.ndarray) -> dict[str, bytes]:
    """Coordinates one after another, each as the least kind that gives its numbers back, and the place of each one's kind."""
    with np.errstate(all="ignore"):
        kinds = np.where((x.astype("<u1") == x).all(0), 0, np.where((x.astype("<f4") == x).all(0), 1, 2)).astype("<u1")
        return {"kinds": kinds.tobytes(), "coords": b"".join(x.T[kinds == k].astype(kind).tobytes() for k, kind in enumerate(KINDS))}


def _wide(row: dict, n: int) -> np.ndarray:
    """d x n coordinates again."""
    kinds, at = np.frombuffer(row["kinds"], "<u1"), 0
    out = np.empty((len(kinds), n))
    for k, kind in enumerate(KINDS):
        own = np.flatnonzero(kinds == k)
        out[own] = np.frombuffer(row["coords"], kind, len(own) * n, at).reshape(len(own), n)
        at += len(own) * n * np.dtype(kind).itemsize
    return out


def stored_blocks(nodes: DataFrame) -> DataFrame:
    """Packed nodes as rows of raw arrays, written once for many scans where they are: BLOCK_PAIRS locations or one node in a row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in packed_batches(batches):
            at = 0
            while at < len(block):
                stop = max(at + 1, int(np.searchsorted(block.offsets, block.offsets[at] + BLOCK_PAIRS, side="right")) - 1)
                part, at = block.take(np.arange(at, stop)), stop
                own = {"counts": np.diff(part.offsets)} | {k: getattr(part, k) for k in FIELDS if k != "counts"}
                row = {k: np.ascontiguousarray(own[k], kind).tobytes() for k, kind in FIELDS.items()} | _narrow(part.coords)
                yield pa.record_batch({k: pa.array([v], pa.binary()) for k, v in row.items()})

    with small_batches(nodes.sparkSession, BATCH_BYTES):
        return kept(nodes.select("node_id", "weight", "mass", "support").mapInArrow(run, ", ".join(f"{k} binary" for k in [*FIELDS, "kinds", "coords"])), "blocks", **STORED)


def _mixed(x: np.ndarray, salt: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x.astype(np.int64).view(np.uint64) + np.uint64(salt * 0x9E3779B97F4A7C15 % (1 << 64))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def _chance(x: np.ndarray) -> np.ndarray:
    """Hashes as numbers above 0 and below 1."""
    return ((x >> np.uint64(12)).astype(float) + 0.5) / (1 << 52)


class _Scan:
    """One stored block, its nodes' offsets, and what runs ask of it; coordinates are rows, so that all runs share a product."""

    def __init__(self, row: dict):
        own = {k: np.frombuffer(row[k], kind) for k, kind in FIELDS.items()}
        self.node_id, self.weight, self.loc_id, self.prob = own["node_id"], own["weight"], own["loc_id"], own["prob"]
        self.offsets = np.r_[0, np.cumsum(own["counts"])]
        self.segment = np.repeat(np.arange(len(self.node_id)), own["counts"])
        self.x = _wide(row, len(self.prob))
        self.w = self.weight[self.segment] * self.prob
        self.square = np.einsum("ij,ij->j", self.x, self.x)

    def steps(self) -> Iterator[slice]:
        return (slice(a, min(a + BLOCK_PAIRS, len(self.prob))) for a in range(0, len(self.prob), BLOCK_PAIRS))

    def gaps(self, at: slice, centres: np.ndarray) -> np.ndarray:
        """Distances of all centres to the pairs, by products; exact ones follow where a location may stand on a centre."""
        gap = (-2 * centres) @ self.x[:, at]
        gap += self.square[at]
        gap += np.einsum("ij,ij->i", centres, centres)[:, None]
        return np.sqrt(np.maximum(gap, 0, out=gap), out=gap)

    def labels(self, sets: list[np.ndarray]) -> list[np.ndarray]:
        """The expected nearest centre of each node, for several sets of centres."""
        centres = np.concatenate(sets)
        sums = np.zeros((len(centres), len(self.node_id)))
        for at in self.steps():
            gap = self.gaps(at, centres)
            gap *= self.prob[at]
            first, last = self.segment[at.start], self.segment[at.stop - 1] + 1
            sums[:, first:last] += np.add.reduceat(gap, np.maximum(self.offsets[first:last], at.start) - at.start, axis=1)
        return [x.argmin(0) for x in np.split(sums, np.cumsum([len(c) for c in sets])[:-1])]

    def apart(self, pairs: np.ndarray, centres: np.ndarray, label: np.ndarray, product: np.ndarray) -> np.ndarray:
        """Each pair's distance to its label's centre, from their product: exact where products aren't."""
        extent = self.square[pairs] + np.einsum("ij,ij->i", centres, centres)[label]
        gap = extent - 2 * product
        close = np.flatnonzero(gap <= 1e-6 * extent)
        gap[close] = ((self.x[:, pairs[close]] - centres[label[close]].T) ** 2).sum(0)
        return np.sqrt(gap)

    def pool(self, keys: np.ndarray, most: int) -> dict:
        """The locations of the smallest keys, without those that can't be taken."""
        at = np.argpartition(keys, most)[:most] if len(keys) > most else np.arange(len(keys))
        at = at[np.isfinite(keys[at])]
        return {"keys": keys[at], "ids": self.loc_id[at], "x": self.x[:, at].T}

    def first(self, seed: int) -> dict:
        keys = np.where(self.w > 0, _chance(_mixed(self.loc_id, seed)), np.inf)
        return self.pool(keys, 1)

    def draws(self, seed: int, turn: int, centres: np.ndarray, most: int) -> dict:
        """A draw without replacement by weight times distance: the first arrivals of exponential clocks."""
        near = np.empty(len(self.prob))
        for at in self.steps():
            label, pairs = self.gaps(at, centres).argmin(0), np.arange(at.start, at.stop)
            near[at] = self.apart(pairs, centres, label, (centres @ self.x[:, at])[label, pairs - at.start])
        rate = self.w * near
        clock = -np.log(_chance(_mixed(self.loc_id ^ _mixed(self.node_id, turn).view(np.int64)[self.segment], seed * 1009 + turn)))
        keys = np.divide(clock, rate, out=np.full(len(rate), np.inf), where=rate > 0)
        return self.pool(keys, most)

    def bounds(self, pairs: np.ndarray, label: np.ndarray, k: int) -> dict:
        low, high = np.full((k, len(self.x)), np.inf), np.full((k, len(self.x)), -np.inf)
        order = np.argsort(label, kind="stable")
        order = order[self.w[pairs[order]] > 0]
        if len(order):
            have, begin = np.unique(label[order], return_index=True)
            x = self.x[:, pairs[order]]
            low[have], high[have] = (f.reduceat(x, begin, axis=1).T for f in (np.minimum, np.maximum))
        return {"low": low, "high": high}

    def sums(self, questions: list[tuple]) -> list[dict]:
        """Of each run's centres, sums over their pairs.

        assigned(centres): mass, weighted sum, cost and bounds; and a mark of the whole assignment.  step(centres, live, at, reach): one
        inverse-distance update of each live centre's pairs round its row of `at`, their cost there, and the pairs that it stands on.
        """
        to, spots, place = self.labels([args[0] for _, args, _ in questions]), [], []
        for kind, args, _ in questions:
            live = np.arange(len(args[0])) if kind == "assigned" else args[1]
            place.append(np.full(len(args[0]), -1))
            place[-1][live] = np.arange(len(live))
            spots.append(args[0] if kind == "assigned" else args[2])
        ends = np.cumsum([0, *(len(c) for c in spots)])
        stack, out = np.concatenate(spots), [None] * len(questions)
        for at in self.steps():
            product = stack @ self.x[:, at]
            spread, found = np.zeros_like(product), []
            for q, (kind, args, _) in enumerate(questions):
                k, label, mine = len(spots[q]), place[q][to[q][self.segment[at]]], slice(ends[q], ends[q + 1])
                own = np.flatnonzero(label >= 0)
                label, pairs = label[own], own + at.start
                w, gap = self.w[pairs], self.apart(pairs, spots[q], label, product[mine][label, own])
                if kind == "assigned":
                    pull, sums = w, {"mass": np.bincount(label, w, k)} | self.bounds(pairs, label, k)
                else:
                    pull = np.where(gap > 0, w / np.where(gap > 0, gap, 1), 0)
                    sums = {"pull": np.bincount(label, pull, k), "on": np.bincount(label, (gap <= args[3][label]) & (w > 0), k)}
                spread[mine][label, own] = pull
                found.append(sums | {"cost": np.bincount(label, w * gap, k)})
            whole = spread @ self.x[:, at].T
            for q, sums in enumerate(found):
                sums["sums"] = whole[ends[q] : ends[q + 1]]
                out[q] = sums if out[q] is None else _joined("step", out[q], sums, 0)
        for q, (kind, _, _) in enumerate(questions):
            if kind == "assigned":
                with np.errstate(over="ignore"):
                    out[q]["mark"] = (_mixed(self.node_id, 11) * (to[q] + 1).astype(np.uint64)).sum(dtype=np.uint64)
        return out

    def answers(self, questions: list[tuple]) -> list[dict]:
        summed = [q for q in questions if q[0] in ("assigned", "step")]
        found = iter(self.sums(summed) if summed else [])
        return [next(found) if q[0] in ("assigned", "step") else getattr(self, q[0])(*q[1]) for q in questions]


def _joined(kind: str, one: dict, two: dict, most: int) -> dict:
    if kind in ("first", "draws"):
        both = {k: np.concatenate([one[k], two[k]]) for k in one}
        order = np.lexsort((both["ids"], both["keys"]))[:most]
        return {k: v[order] for k, v in both.items()}
    with np.errstate(over="ignore"):
        return {k: np.minimum(v, two[k]) if k == "low" else np.maximum(v, two[k]) if k == "high" else v + two[k] for k, v in one.items()}


def scanned(blocks: DataFrame, questions: list[tuple]) -> list[dict | None]:
    """The merged answers to (kind, arguments, most rows kept) in one pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        answers: list = [None] * len(questions)
        for batch in batches:
            for i in range(batch.num_rows):
                block = _Scan({k: batch.column(k)[i].as_buffer() for k in batch.schema.names})
                for q, own in enumerate(block.answers(questions)):
                    answers[q] = own if answers[q] is None else _joined(questions[q][0], answers[q], own, questions[q][2])
        if any(x is not None for x in answers):
            yield pa.record_batch({"part": pa.array([TaskContext.get().partitionId()], pa.int32()), "answers": pa.array([pickle.dumps(answers)], pa.binary())})

    merged: list = [None] * len(questions)
    with small_batches(blocks.sparkSession, BATCH_BYTES):
        rows = blocks.mapInArrow(run, "part int, answers binary").collect()
    for row in sorted(rows, key=lambda r: r["part"]):
        for q, own in enumerate(pickle.loads(row["answers"])):
            merged[q] = own if merged[q] is None else _joined(questions[q][0], merged[q], own, questions[q][2])
    return merged


def _seeds(k: int, seed: int) -> Generator[tuple, dict | None, np.ndarray]:
    """Up to k locations by weight times distance; a scan's candidates give as many seeds as there are already.

    Candidates come by their weight and the distance to the seeds before the scan; those that a newer seed is nearer to are
    taken with their share of that distance, so that the draws follow the newest distances.
    """
    found = yield "first", (seed,), 1
    if found is None or not len(found["keys"]):
        return np.zeros((0, 0))
    centres, turn, rng = found["x"].copy(), 0, np.random.default_rng(seed)
    while len(centres) < k:
        turn += 1
        wanted = min(k - len(centres), len(centres))
        pool = yield "draws", (seed, turn, centres, POOL * wanted), POOL * wanted
        x = pool["x"]
        if not len(x):  # fewer than k different locations
            break
        old = kernels.distances(x, centres).min(1)
        now, free = old.copy(), np.ones(len(x), bool)
        for _ in range(wanted):
            share = np.where(free, now / old, 0)
            if share.sum() <= 0:
                break
            taken = np.flatnonzero(rng.random(len(x)) < share)
            at = int(taken[0]) if len(taken) else int(share.argmax())
            centres, free[at] = np.r_[centres, x[at : at + 1]], False
            now = np.minimum(now, kernels.distances(x, x[at : at + 1])[:, 0])
    return centres


def _run(k: int, seed: int, restarts: int, profile: Profile, max_rounds: int) -> Generator[tuple, dict | None, tuple[np.ndarray, float, int]]:
    """The rules of `kernels.solve_assigned`; an iterate that stands on a location stays there."""
    best: tuple = (np.zeros((0, 0)), 0.0, 0)
    for r in range(restarts):
        centres = yield from _seeds(k, seed + 7919 * r)
        if not len(centres):
            return best
        mark, rounds = None, 0
        now = yield "assigned", (centres,), 0
        while rounds < max_rounds and now["mark"] != mark:
            mark, rounds = now["mark"], rounds + 1
            have = now["mass"] > 0
            y = np.where(have[:, None], now["sums"] / np.where(have, now["mass"], 1)[:, None], centres)
            reach = np.where(have, kernels.COINCIDES * np.sqrt((np.where(have[:, None], now["high"] - now["low"], 0) ** 2).sum(1)), 0)
            live, goes, before, cost, steps = have.copy(), have, np.zeros(len(y)), np.zeros(len(y)), 0
            while live.any():
                own = np.flatnonzero(live)  # the others' pairs are left out; their cost is known
                turn = yield "step", (centres, own, y[own], reach[own]), 0
                cost[own] = turn["cost"]
                live[own] = (turn["on"] == 0) & (turn["pull"] > 0) & (steps < profile.max_steps)
                new = y.copy()
                new[own] = np.where(live[own, None], turn["sums"] / np.where(turn["pull"] > 0, turn["pull"], 1)[:, None], y[own])
                step = np.sqrt(((new - y) ** 2).sum(1))
                if steps >= 2:  # the newest step was made already; the rule looks at the two before it
                    live &= goes
                    new = np.where(live[:, None], new, y)
                if not live.any():
                    break
                goes = step > SETTLED * reach / kernels.COINCIDES
                if profile.stop == "step_ratio":  # steps that become a tenth each time would reach the last bits of a number, a scan each
                    goes &= (before > 0) & (step <= profile.ratio * before)
                goes |= steps < 1
                y, before, steps = new, step, steps + 1
            centres = np.where((have & ((cost <= now["cost"]) | (not profile.guard)))[:, None], y, centres)
            now = yield "assigned", (centres,), 0
        cost = float(now["cost"].sum())
        if not r or cost < best[1]:
            best = centres, cost, rounds
    return best


def solve_full(nodes: DataFrame, runs: list[tuple[int, int]], restarts: int = 1, profile: Profile = PRACTICAL, max_rounds: int = 10) -> dict[tuple[int, int], tuple[np.ndarray, float, int]]:
    """{(k, seed): (centres, cost, rounds)} of the whole-node solver on all nodes; a scan serves all runs that go on."""
    blocks, out = stored_blocks(nodes), {}
    live = {run: _run(*run, restarts, profile, max_rounds) for run in runs}
    questions = {run: next(g) for run, g in live.items()}
    while questions:
        answers = dict(zip(questions, scanned(blocks, list(questions.values())), strict=True))
        for run, answer in answers.items():
            try:
                questions[run] = live[run].send(answer)
            except StopIteration as e:
                out[run] = e.value
                del questions[run]
    return out
