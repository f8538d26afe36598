"""Numpy kernels on a bounded set of nodes; the tasks of Arrow stages and the local solvers call them.

A `Block` holds nodes with ragged supports.  All randomness comes from a seed, so a retried task repeats its result.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import product

import numpy as np
import pyarrow as pa

from .model import Profile

#: Relative distance at which an iterate counts as standing on a location.
COINCIDES = 1e-12
STATUS = ("closed_form", "converged", "capped", "ratio_stop", "fallback")


@dataclass
class Block:
    node_id: np.ndarray
    weight: np.ndarray
    mass: np.ndarray
    offsets: np.ndarray
    loc_id: np.ndarray
    coords: np.ndarray
    prob: np.ndarray
    median: np.ndarray | None = None
    spread: np.ndarray | None = None
    copies: np.ndarray | None = None
    level: np.ndarray | None = None
    cell: np.ndarray | None = None
    _segment: np.ndarray | None = field(default=None, repr=False)

    def __len__(self) -> int:
        return len(self.node_id)

    @property
    def segment(self) -> np.ndarray:
        if self._segment is None:
            self._segment = np.repeat(np.arange(len(self)), np.diff(self.offsets))
        return self._segment

    @property
    def pair_weight(self) -> np.ndarray:
        return self.weight[self.segment] * self.prob

    def take(self, at: np.ndarray) -> Block:
        counts = np.diff(self.offsets)[at]
        offsets = np.r_[0, np.cumsum(counts)]
        rows = np.arange(offsets[-1]) - np.repeat(offsets[:-1] - self.offsets[at], counts)
        own = {k: None if (v := getattr(self, k)) is None else v[at] for k in ("median", "spread", "copies", "level", "cell")}
        return Block(self.node_id[at], self.weight[at], self.mass[at], offsets, self.loc_id[rows], self.coords[rows], self.prob[rows], **own)

    @staticmethod
    def join(parts: list[Block]) -> Block:
        parts = [x for x in parts if len(x)]
        if len(parts) == 1:
            return parts[0]
        shifts = np.cumsum([0, *(x.offsets[-1] for x in parts)])
        offsets = np.r_[0, np.concatenate([x.offsets[1:] + s for x, s in zip(parts, shifts[:-1], strict=True)])]
        one = {k: np.concatenate([getattr(x, k) for x in parts]) for k in ("node_id", "weight", "mass", "loc_id", "coords", "prob")}
        own = {k: np.concatenate(v) if all(x is not None for x in v) else None for k in ("median", "spread", "copies", "level", "cell") for v in [[getattr(x, k) for x in parts]]}
        return Block(offsets=offsets, **one, **own)


def from_arrow(batch: pa.RecordBatch | pa.Table) -> Block:
    table = pa.Table.from_batches([batch]) if isinstance(batch, pa.RecordBatch) else batch
    table = table.combine_chunks()
    column = {name: (c.chunk(0) if c.num_chunks else c.combine_chunks()) for name, c in zip(table.column_names, table.columns, strict=True)}
    support = column["support"]
    offsets = support.offsets.to_numpy().astype(np.int64)
    items = support.flatten()
    coords = items.field("coords")
    d = len(coords.flatten()) // max(len(coords), 1)
    own = {}
    if "median" in column:
        own["median"] = column["median"].flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
        own["spread"] = column["spread"].to_numpy(zero_copy_only=False)
        own["level"], own["copies"] = (column[k].to_numpy(zero_copy_only=False) for k in ("level", "copies"))
        own["cell"] = np.stack([column["cell"].field(k).to_numpy(zero_copy_only=False) for k in ("centre", "ring", "spread")], 1)
    numpy = lambda x: x.to_numpy(zero_copy_only=False)
    return Block(numpy(column["node_id"]), numpy(column["weight"]), numpy(column["mass"]), offsets - offsets[0], numpy(items.field("loc_id")), numpy(coords.flatten()).reshape(-1, d), numpy(items.field("prob")), **own)


def to_arrow(block: Block) -> pa.RecordBatch:
    """Rows of the summary schema."""
    n, d = len(block), block.coords.shape[1]
    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(block.coords) + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(block.coords).ravel()))
    items = pa.StructArray.from_arrays([pa.array(block.loc_id, pa.int64()), lists, pa.array(block.prob)], ["loc_id", "coords", "prob"])
    cell = block.cell if block.cell is not None else np.zeros((n, 3), np.int32)
    return pa.record_batch({
        "node_id": pa.array(block.node_id, pa.int64()), "weight": pa.array(block.weight, pa.float64()), "mass": pa.array(block.mass, pa.float64()),
        "support": pa.ListArray.from_arrays(pa.array(block.offsets.astype(np.int32)), items),
        "median": pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(block.median).ravel())),
        "spread": pa.array(block.spread, pa.float64()), "level": pa.array(block.level, pa.int32()), "copies": pa.array(block.copies, pa.int32()),
        "cell": pa.StructArray.from_arrays([pa.array(cell[:, k].astype(np.int32)) for k in range(3)], ["centre", "ring", "spread"]),
    })


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Euclidean distances of all rows of x to all rows of c, in blocks of bounded memory."""
    out = np.empty((len(x), len(c)))
    step = max(1, (1 << 22) // max(1, len(c) * x.shape[1]))
    for k in range(0, len(x), step):
        part = x[k : k + step, None, :] - c[None, :, :]
        out[k : k + step] = np.sqrt(np.einsum("ijk,ijk->ij", part, part))
    return out


def _sums(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    return np.add.reduceat(values, starts, axis=0)


def iterative_medians(x: np.ndarray, w: np.ndarray, offsets: np.ndarray, stop: str = "step_ratio", ratio: float = 0.1, max_steps: int = 15, tolerance: float = 1e-9) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(medians, updates made, status index) of ragged weighted point sets, all at once.

    Starts at the centres of gravity.  Two updates are always made, for the step ratio needs three iterates; then
    'step_ratio' goes on while the newest step is at most `ratio` of the one before, 'step_tolerance' until
    a step is at most `tolerance` of the set's extent.  A set of one location is its own median; an iterate on a location of a larger
    set ends with status fallback.
    """
    counts, starts = np.diff(offsets), offsets[:-1]
    n = len(counts)
    y = _sums(w[:, None] * x, starts) / _sums(w, starts)[:, None]
    extent = np.sqrt(((np.maximum.reduceat(x, starts) - np.minimum.reduceat(x, starts)) ** 2).sum(1))
    steps, status, before = np.zeros(n, int), np.full(n, 2), np.zeros(n)
    single = (counts == 1) | (extent == 0)
    y[single], status[single] = x[starts[single]], 0
    # Closed forms: the heavier of two locations (their middle on a tie), the weighted median on a line.
    two = np.flatnonzero((counts == 2) & ~single)
    first, second = w[starts[two]], w[starts[two] + 1]
    y[two] = np.where((first == second)[:, None], y[two], x[starts[two] + (second > first)])
    status[two] = 0
    if x.shape[1] == 1 and n:
        segment = np.repeat(np.arange(n), counts)
        order = np.lexsort((x[:, 0], segment))
        before = np.cumsum(w[order])
        base = np.r_[0, before][starts]
        half = base + _sums(w, starts) / 2
        at = np.minimum(np.searchsorted(before, half * (1 - 1e-12)), offsets[1:] - 1)
        y[:, 0], status[:] = x[order[at], 0], 0
    single = status == 0
    live = np.flatnonzero(~single)
    while len(live):
        own = counts[live]
        begin = np.r_[0, np.cumsum(own)[:-1]]
        rows = np.arange(own.sum()) - np.repeat(begin - starts[live], own)
        gap = np.sqrt(((x[rows] - np.repeat(y[live], own, 0)) ** 2).sum(1))
        on = np.logical_or.reduceat(gap <= COINCIDES * np.repeat(extent[live], own), begin)
        status[live[on]] = 4
        pull = w[rows] / np.where(gap > 0, gap, 1)
        new = _sums(pull[:, None] * x[rows], begin) / _sums(pull, begin)[:, None]
        step = np.sqrt(((new - y[live]) ** 2).sum(1))
        y[live[~on]] = new[~on]
        steps[live[~on]] += 1
        count, last = steps[live], before[live]
        still = count < 2
        if stop == "step_ratio":
            goes = still | ((last > 0) & (step <= ratio * np.where(last > 0, last, 1)))
            status[live[~goes & ~on]] = np.where(last[~goes & ~on] == 0, 1, 3)
        else:
            goes = still | (step > tolerance * extent[live])
            status[live[~goes & ~on]] = 1
        before[live] = step
        live = live[goes & ~on & (count < max_steps)]
    return y, steps, status


def copies_of(pair_weight: np.ndarray, prob: np.ndarray, weight: np.ndarray, eps: float) -> np.ndarray:
    """Multiplicity of each location in the unweighted multiset that stands for a weighted one; nodes of weight 0 have none."""
    some, there = weight[weight > 0], prob[prob > 0]
    if not len(some) or not len(there):
        return np.zeros(len(prob))
    return np.floor(pair_weight / (min(some.min(), 1.0) * there.min() * eps))


def sampled_median(x: np.ndarray, copies: np.ndarray, rng: np.random.Generator, confidence: float = 0.9, gamma: float = 0.5, n_eval: int = 64, repeats: int = 1, candidates: str = "support", eps: float = 0.5) -> np.ndarray:
    """A point whose cost is at most 2 (1 + gamma) times the least with chance `confidence`, at a cost that doesn't depend on len(x).

    Candidates are drawn by multiplicity and scored on an independent draw; 'lattice' adds the points of a grid round
    each candidate, which comes arbitrarily near the optimum for a low dimension.
    """
    chance = copies / copies.sum() if copies.sum() > 0 else np.full(len(x), 1 / len(x))
    n = int(np.ceil(np.log(1 / (1 - confidence)) * (1 + gamma) / gamma))
    best, least = x[0], np.inf
    for _ in range(repeats):
        tried = x[rng.choice(len(x), n, p=chance)]
        judges = x[rng.choice(len(x), n_eval, p=chance)]
        if candidates == "lattice":
            reach = distances(tried, judges).mean(1).min()
            side = eps * reach / np.sqrt(x.shape[1])
            ticks = np.arange(-np.ceil(1 / eps), np.ceil(1 / eps) + 1) * side
            grid = np.array(list(product(ticks, repeat=x.shape[1]))) if len(ticks) ** x.shape[1] <= 4096 else rng.normal(0, reach, (4096, x.shape[1]))
            tried = np.concatenate([tried, *(c + grid for c in tried[:4])])
        cost = distances(tried, judges).mean(1)
        k = int(cost.argmin())
        if cost[k] < least:
            best, least = tried[k], cost[k]
    return best


def support_median(x: np.ndarray, w: np.ndarray) -> int:
    """Index of the location of least weighted distance to all."""
    return int((distances(x, x) * w[None, :]).sum(1).argmin())


def node_medians(block: Block, profile: Profile, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(medians, spreads, steps, status) of all nodes; a spread is the mean distance to the median, by mass.

    Nodes that are to be sampled (all under 'sampled', those of more than dense_threshold locations else) are never iterated,
    so that their cost doesn't depend on their support.
    """
    counts = np.diff(block.offsets)
    sampled = (counts > 1) & ((counts > profile.dense_threshold) | (profile.median == "sampled"))
    y, steps, status = np.zeros((len(block), block.coords.shape[1])), np.zeros(len(block), int), np.full(len(block), 4)
    rest = np.flatnonzero(~sampled)
    if len(rest):
        own = block.take(rest) if sampled.any() else block
        y[rest], steps[rest], status[rest] = iterative_medians(own.coords, own.prob, own.offsets, profile.stop, profile.ratio, profile.max_steps)
    again = np.flatnonzero(status == 4)
    if len(again):
        copies = copies_of(block.pair_weight, block.prob, block.weight, profile.eps)
        repeats = profile.repeats_for(len(block))
        for k in again:
            a, b = block.offsets[k], block.offsets[k + 1]
            rng = np.random.default_rng([seed, int(block.node_id[k]) & 0x7FFFFFFF])
            often = copies[a:b] if copies[a:b].sum() > 0 else block.prob[a:b]  # a weight of 0 cancels in a median
            y[k] = sampled_median(block.coords[a:b], often, rng, profile.confidence, repeats=repeats, candidates=profile.candidates, eps=profile.eps)
    return y, spreads(block, y), steps, status


def spreads(block: Block, y: np.ndarray) -> np.ndarray:
    gap = np.sqrt(((block.coords - y[block.segment]) ** 2).sum(1))
    return _sums(block.prob * gap, block.offsets[:-1]) / block.mass


def seed_points(x: np.ndarray, w: np.ndarray, k: int, rng: np.random.Generator, power: int = 1, uniform_first: bool = True) -> np.ndarray:
    """Indices of up to k centres: the first uniform, the next by weight times distance^power to the nearest chosen."""
    chosen = [int(rng.integers(len(x)) if uniform_first else rng.choice(len(x), p=w / w.sum()))]
    near = distances(x, x[chosen])[:, 0]
    while len(chosen) < k:
        mass = w * near**power
        total = mass.sum()
        if total <= 0:  # fewer than k different locations
            break
        chosen.append(int(np.searchsorted(np.cumsum(mass), rng.random() * total, side="right").clip(0, len(x) - 1)))
        near = np.minimum(near, distances(x, x[chosen[-1:]])[:, 0])
    return np.array(chosen)


def grouped_medians(x: np.ndarray, w: np.ndarray, label: np.ndarray, k: int, old: np.ndarray, guard: bool, profile: Profile) -> np.ndarray:
    """The median of each label's points; an empty label keeps its old centre, and so does one that got no cheaper under `guard`."""
    out = old.copy()
    order = np.argsort(label, kind="stable")
    order = order[w[order] > 0]
    if not len(order):
        return out
    have, first = np.unique(label[order], return_index=True)
    offsets = np.r_[first, len(order)]
    y, _, status = iterative_medians(x[order], w[order], offsets, profile.stop, profile.ratio, profile.max_steps)
    for j in np.flatnonzero(status == 4):  # an iterate on a location: the sampled median of the group
        a, b = offsets[j], offsets[j + 1]
        y[j] = sampled_median(x[order[a:b]], w[order[a:b]], np.random.default_rng([int(have[j]), len(order)]), profile.confidence, repeats=profile.repeats_for(len(have)))
    if guard:
        own = np.repeat(np.arange(len(have)), np.diff(offsets))
        cost = [_sums(w[order] * np.sqrt(((x[order] - c[own]) ** 2).sum(1)), offsets[:-1]) for c in (y, old[have])]
        y = np.where((cost[0] <= cost[1])[:, None], y, old[have])
    out[have] = y
    return out


def _reseed(centres: np.ndarray, label: np.ndarray, x: np.ndarray, gap: np.ndarray, empty: str) -> None:
    if empty == "reseed":
        for j in np.setdiff1d(np.arange(len(centres)), label):
            centres[j] = x[int(gap.argmax())]


def kmedian_lloyd(x: np.ndarray, w: np.ndarray, k: int, seed: int, profile: Profile, power: int = 1) -> np.ndarray:
    """Centre search: distance-proportional seeding, then assignment and medians until nothing moves or max_rounds."""
    rng = np.random.default_rng(seed)
    w_seed = w if profile.weighted_seeding else np.ones(len(x))
    centres = x[seed_points(x, w_seed, k, rng, power)].astype(float)
    label = np.full(len(x), -1)
    for _ in range(profile.max_rounds):
        gap = distances(x, centres)
        new = gap.argmin(1)
        if (new == label).all():
            break
        label = new
        centres = grouped_medians(x, w, label, len(centres), centres, profile.guard, profile)
        _reseed(centres, label, x, gap.min(1), profile.empty)
    return centres


def kmeans(x: np.ndarray, w: np.ndarray, k: int, seed: int, plusplus: bool = True, max_rounds: int = 10) -> np.ndarray:
    rng = np.random.default_rng(seed)
    at = seed_points(x, w, k, rng, 2, uniform_first=False) if plusplus else rng.choice(len(x), min(k, len(x)), replace=False)
    centres, label = x[at].astype(float), np.full(len(x), -1)
    for _ in range(max_rounds):
        new = distances(x, centres).argmin(1)
        if (new == label).all():
            break
        label = new
        whole = np.bincount(label, w, len(centres))
        for j in np.flatnonzero(whole > 0):
            own = label == j
            centres[j] = (w[own, None] * x[own]).sum(0) / whole[j]
    return centres


def sampled_bicriteria(x: np.ndarray, w: np.ndarray, k: int, seed: int, profile: Profile) -> np.ndarray:
    """At most 2k centres: k of a sample of about sqrt(n k log k), and k of the points that those serve worst."""
    n = len(x)
    size = int(min(n, max(4 * k, np.ceil(np.sqrt(n * k * max(1.0, np.log(k)))))))
    if size >= n:
        return kmedian_lloyd(x, w, k, seed, profile)
    rng = np.random.default_rng([seed, 1])
    at = rng.choice(n, size, replace=False)
    first = kmedian_lloyd(x[at], w[at], k, seed, profile)
    far = distances(x, first).min(1)
    tail = np.argsort(-far, kind="stable")[: min(n, max(2 * k, int(np.ceil(n * k * max(1.0, np.log(k)) / size))))]
    return np.concatenate([first, kmedian_lloyd(x[tail], w[tail], k, seed + 1, profile)])


def classes(values: np.ndarray, radius: float, closed_low: bool) -> np.ndarray:
    """Ring or spread class by exact powers of two; closed_low: 2^(h-1) R belongs to class h, else to h - 1."""
    if radius <= 0:
        return np.zeros(len(values), int)
    top = max(1, int(np.ceil(np.log2(max(float(values.max(initial=0)) / radius, 1)))) + 2)
    return np.searchsorted(radius * 2.0 ** np.arange(top), values, side="right" if closed_low else "left")


def radius_unit(block: Block, gap: np.ndarray, alpha: float, basis: str) -> float:
    """Estimated expected cost over alpha times the expected weight."""
    expected = block.weight * block.mass
    value = gap + block.spread if basis == "location_spread" else gap
    total = expected.sum()
    return float((expected * value).sum() / (alpha * total)) if total > 0 else 0.0


def cells(block: Block, centres: np.ndarray, profile: Profile) -> tuple[np.ndarray, float]:
    """(centre, ring, spread class) of every node and the radius unit."""
    gap = distances(block.median, centres)
    nearest = gap.argmin(1)
    gap = gap[np.arange(len(block)), nearest]
    radius = radius_unit(block, gap, profile.alpha, profile.basis)
    return np.stack([nearest, classes(gap, radius, True), classes(block.spread, radius, False)], 1).astype(np.int32), radius


def draws_per_cell(sizes: np.ndarray, k: int, per_k: int, allotment: str) -> np.ndarray:
    if allotment == "even":
        return np.full(len(sizes), max(per_k * k // len(sizes), 1))
    if allotment == "as_printed":
        return np.maximum(per_k * k // sizes, 1)
    return np.maximum((per_k * k * sizes) // sizes.sum(), 1)


def draw(block: Block, of: np.ndarray, k: int, profile: Profile, seed: int) -> Block:
    """Draws with replacement in every cell; copies are merged, and weights make the cost unbiased."""
    _, inverse, sizes = np.unique(of, axis=0, return_inverse=True, return_counts=True)
    inverse = inverse.ravel()
    s = draws_per_cell(sizes, k, profile.per_k, profile.allotment)
    chance = {"weight": block.weight, "expected_weight": block.weight * block.mass, "uniform": np.ones(len(block))}[profile.draw_mass]
    order = np.lexsort((block.node_id, inverse))
    starts = np.r_[0, np.cumsum(sizes)]
    rng = np.random.default_rng([seed, 2])
    kept, weights, copies = [], [], []
    for c in range(len(sizes)):
        own = order[starts[c] : starts[c + 1]]
        mass = chance[own]
        total = mass.sum()
        if (profile.exhaust_small and s[c] >= len(own)) or total <= 0:
            kept.append(own), weights.append(block.weight[own]), copies.append(np.ones(len(own), int))
            continue
        hit = np.searchsorted(np.cumsum(mass), rng.random(s[c]) * total, side="right").clip(0, len(own) - 1)
        at, times = np.unique(hit, return_counts=True)
        kept.append(own[at]), copies.append(times)
        weights.append(times * block.weight[own[at]] * total / (s[c] * mass[at]))
    at = np.concatenate(kept)
    out = block.take(at)
    out.weight, out.copies, out.cell = np.concatenate(weights), np.concatenate(copies), of[at]
    return out


def compress_support(block: Block, profile: Profile, seed: int) -> Block:
    """Each node's own distribution by draws in rings round its median; a ring's mass is kept exactly."""
    count = max(8, int(np.ceil(np.log(max(len(block), 2) / profile.delta) / profile.eps**2)))
    rows, probs, offsets = [], [], [0]
    for k in range(len(block)):
        a, b = int(block.offsets[k]), int(block.offsets[k + 1])
        gap = np.sqrt(((block.coords[a:b] - block.median[k]) ** 2).sum(1))
        ring = classes(gap, float(block.spread[k]), True)
        rng = np.random.default_rng([seed, 3, int(block.node_id[k]) & 0x7FFFFFFF])
        own: dict[int, float] = {}
        for r in np.unique(ring):
            at = np.flatnonzero(ring == r)
            mass = block.prob[a:b][at]
            if len(at) <= count:
                hits, share = at, mass
            else:
                picked, times = np.unique(rng.choice(len(at), count, p=mass / mass.sum()), return_counts=True)
                hits, share = at[picked], times * mass.sum() / count
            for h, p in zip(hits, share, strict=True):
                own[int(h)] = own.get(int(h), 0.0) + float(p)
        rows += [a + h for h in own]
        probs += own.values()
        offsets.append(len(rows))
    at = np.array(rows)
    return Block(block.node_id, block.weight, block.mass, np.array(offsets), block.loc_id[at], block.coords[at], np.array(probs), block.median, block.spread, block.copies, block.level, block.cell)


def with_medians(block: Block, profile: Profile, seed: int) -> Block:
    """Medians and spreads are computed once for a node and carried along: its weight doesn't change them."""
    if block.median is None:
        block.median, block.spread, _, _ = node_medians(block, profile, seed)
        block.level, block.copies = np.zeros(len(block), np.int32), np.ones(len(block), np.int32)
        block.cell = np.zeros((len(block), 3), np.int32)
    return block


def reduce_block(block: Block, k: int, profile: Profile, seed: int) -> Block:
    """One reduction: medians, candidate centres, cells, draws and, if asked for, support compression."""
    block = with_medians(block, profile, seed)
    if len(block) <= profile.per_k * k:  # the budget takes everything
        return block
    search = sampled_bicriteria if profile.centres == "sampled_bicriteria" else kmedian_lloyd
    found = [search(block.median, block.weight, k, seed + 101 * r, profile) for r in range(profile.repeats_for(len(block)))]
    cost = [(block.weight * distances(block.median, c).min(1)).sum() for c in found] if len(found) > 1 else [0]
    of, _ = cells(block, found[int(np.argmin(cost))], profile)
    level = int(block.level.max(initial=0)) + 1
    out = draw(block, of, k, profile, seed)
    out.level = np.full(len(out), level, np.int32)
    if profile.compress_support:
        out = compress_support(out, profile, seed)
        out.median, out.spread, _, _ = node_medians(out, profile, seed)
    return out


class Ladder:
    """Merge and reduce: level 0 collects raw nodes, level j holds a summary of 2^(j-1) full buckets, as a binary counter."""

    def __init__(self, k: int, profile: Profile, seed: int):
        self.k, self.profile, self.seed = k, profile, seed
        self.capacity = profile.capacity_for(k)
        self.buffer: list[Block] = []
        self.held = self.reductions = self.seen = 0
        self.levels: list[Block | None] = []

    def add(self, block: Block) -> None:
        at = 0
        while at < len(block):
            n = min(self.capacity - self.held, len(block) - at)
            self.buffer.append(block.take(np.arange(at, at + n)))
            self.held, self.seen, at = self.held + n, self.seen + n, at + n
            if self.held == self.capacity:
                full = with_medians(Block.join(self.buffer), self.profile, self.seed)
                self.buffer, self.held = [], 0
                self.carry(full)

    def carry(self, block: Block) -> None:
        j = 0
        while j < len(self.levels) and self.levels[j] is not None:
            block = self.reduced(Block.join([self.levels[j], block]))
            self.levels[j] = None
            j += 1
        if j == len(self.levels):
            self.levels.append(None)
        self.levels[j] = block

    def reduced(self, block: Block) -> Block:
        self.reductions += 1
        return reduce_block(block, self.k, self.profile, self.seed * 1_000_003 + self.reductions)

    def occupancy(self) -> list[int]:
        """Nodes that each level stands for: level 0 raw nodes, then full buckets by binary digits."""
        return [self.held, *(int(x is not None) for x in self.levels)]

    def finish(self) -> Block | None:
        parts = [x for x in self.levels if x is not None]
        if self.buffer:
            parts.append(self.reduced(Block.join(self.buffer)))
        return Block.join(parts) if parts else None


def expected_distances(block: Block, centres: np.ndarray) -> np.ndarray:
    """n x k: sum of probability times distance; a node that is unrealised with chance 1 - mass costs nothing then."""
    out = np.empty((len(block), len(centres)))
    step = max(1, (1 << 20) // max(1, int(np.diff(block.offsets).max(initial=1)) * len(centres)))
    for k in range(0, len(block), step):
        a, b = block.offsets[k], block.offsets[min(k + step, len(block))]
        gap = distances(block.coords[a:b], centres) * block.prob[a:b, None]
        out[k : k + step] = _sums(gap, block.offsets[k : min(k + step, len(block))] - a)
    return out


def assigned_cost(block: Block, centres: np.ndarray) -> float:
    return float((block.weight * expected_distances(block, centres).min(1)).sum())


def solve_assigned(block: Block, k: int, seed: int, profile: Profile, restarts: int = 1, max_rounds: int = 10) -> tuple[np.ndarray, float, int]:
    """(centres, cost, rounds) of the whole-node solver; the cheapest of `restarts` runs.

    Seeds are locations by total realisation weight times distance; a node goes whole to its expected nearest
    centre, and a centre moves to the median of all realisations of its nodes.
    """
    location, first, inverse = np.unique(block.loc_id, return_index=True, return_inverse=True)
    x = block.coords[first]
    mass = np.bincount(inverse.ravel(), block.pair_weight, len(location))
    x, mass = x[mass > 0], mass[mass > 0]
    best: tuple = (None, np.inf, 0)
    for r in range(restarts):
        rng = np.random.default_rng([seed, r])
        centres = x[seed_points(x, mass, k, rng)].astype(float)
        label, rounds = np.full(len(block), -1), 0
        while rounds < max_rounds:
            gap = expected_distances(block, centres)
            new = gap.argmin(1)
            if (new == label).all():
                break
            label, rounds = new, rounds + 1
            centres = grouped_medians(block.coords, block.pair_weight, label[block.segment], len(centres), centres, profile.guard, profile)
            _reseed(centres, label, block.median if block.median is not None else block.coords[block.offsets[:-1]], gap.min(1), profile.empty)
        cost = assigned_cost(block, centres)
        if cost < best[1]:
            best = centres, cost, rounds
    return best


def exact_small(block: Block, k: int) -> tuple[np.ndarray, float]:
    """The optimum of at most 8 nodes and 3 centres by all assignments, each group's median to 1e-10."""
    assert len(block) <= 8 and k <= 3
    tight = Profile(stop="step_tolerance", max_steps=20_000)
    best: tuple = (None, np.inf)
    for label in product(range(k), repeat=len(block)):
        label = np.array(label)
        start = np.array([block.coords[block.segment == int(np.flatnonzero(label == j)[0])].mean(0) if (label == j).any() else block.coords[0] for j in range(k)])
        centres = grouped_medians(block.coords, block.pair_weight, label[block.segment], k, start, False, tight)
        for j in range(k):  # a median may be a location, where the iteration has no successor
            own = (label[block.segment] == j).nonzero()[0]
            if len(own):
                x, w = block.coords[own], block.pair_weight[own]
                s = x[support_median(x, w)]
                if (w * np.sqrt(((x - s) ** 2).sum(1))).sum() < (w * np.sqrt(((x - centres[j]) ** 2).sum(1))).sum():
                    centres[j] = s
        cost = assigned_cost(block, centres)
        if cost < best[1]:
            best = centres, cost
    return best


# --- uncertain join ---------------------------------------------------------------------------------------------------

#: Points of each side of a block of pairs, so that its differences stay in the processor's cache.
PAIR_SIDE = 128


def match_totals(x: np.ndarray, x_copies: np.ndarray, y: np.ndarray, y_copies: np.ndarray, slope: float) -> tuple[np.ndarray, np.ndarray]:
    """(sum, number) of the positive scores 1 - slope * (L1 distance) of each point of x against all copies of y, and of y against x.

    If y is x itself, each pair is looked at once.  Distances are added up in the order of the coordinates, as an SQL fold adds them.
    """
    same, xs, ys = y is x, np.ascontiguousarray(x.T), np.ascontiguousarray(y.T)
    x_copies, y_copies = x_copies.astype(float), y_copies.astype(float)
    of_x = np.zeros((len(x), 2))
    of_y = of_x if same else np.zeros((len(y), 2))
    for i in range(0, len(x), PAIR_SIDE):
        a = slice(i, i + PAIR_SIDE)
        for j in range(i if same else 0, len(y), PAIR_SIDE):
            b = slice(j, j + PAIR_SIDE)
            gap = np.zeros((len(x_copies[a]), len(y_copies[b])))
            part = np.empty_like(gap)
            for p, q in zip(xs[:, a], ys[:, b], strict=True):
                np.subtract.outer(p, q, out=part)
                gap += np.abs(part, out=part)
            score = np.maximum(1.0 - slope * gap, 0.0, out=gap)
            hit = np.greater(score, 0.0, out=part, casting="unsafe")
            of_x[a, 0] += score @ y_copies[b]
            of_x[a, 1] += hit @ y_copies[b]
            if not same or j > i:
                of_y[b, 0] += x_copies[a] @ score
                of_y[b, 1] += x_copies[a] @ hit
    return of_x, of_y
