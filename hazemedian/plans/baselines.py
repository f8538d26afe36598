"""Methods to compare with: full-data solver, k-means kinds, stream k-means++, feature tree, collapses, uniform sample."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..functions.expressions import portable_uniform
from ..model import PRACTICAL
from ..operators import centres as centre_ops
from ..operators.costs import nearest_centre_nodes
from ..operators.medians import group_centroids, group_updates
from ..operators.nodes import unpack
from ..sources.tables import kept

POINT = "coords array<double>, weight double"


def full_solver(nodes: DataFrame, k: int, d: int, seed: int = 1, rounds: int = 10, updates: int = 2) -> tuple[list[list[float]], list[int]]:
    """The whole-node solver on the full input as a distributed loop; (centres, moved nodes of each round).

    Seeds from locations by total realisation weight times distance; each round is an assignment by grouped sums and a few small
    aggregates.  Assignments are written to the shared folder each round, which cuts the lineage.
    """
    real = kept(unpack(nodes), "realisations")
    score = real.groupBy("coords").agg(F.min("loc_id").alias("node_id"), F.sum(F.col("weight") * F.col("prob")).alias("weight"))
    if real.isEmpty():
        return [], []
    found = [c for _, c in centre_ops.seed_centres(score, k, d, 1, F.col("weight"), seed)]
    old, moved = None, []
    for _ in range(rounds):
        now = kept(nearest_centre_nodes(real, found, d).select("node_id", F.col("centre_id").alias("centre")), "assignment")
        if old is not None:
            moved.append(now.join(old.withColumnRenamed("centre", "was"), "node_id").where("centre <> was").count())
            if moved[-1] == 0:
                break
        old = now
        rows = real.join(now, "node_id")
        w = F.col("weight") * F.col("prob")
        y = group_centroids(rows, "centre", w, d)
        for _ in range(updates):
            y = y.join(F.broadcast(group_updates(rows, "centre", w, d, y, True).withColumnRenamed("y", "z")), "centre").select("centre", F.coalesce("z", "y").alias("y"))
        got = {x["centre"]: list(x["y"]) for x in y.collect()}
        found = [got.get(i, c) for i, c in enumerate(found)]
    return found, moved


def full_solver_local(nodes: DataFrame, k: int, seed: int = 1, restarts: int = 1) -> tuple[np.ndarray, float, int]:
    """The same on one task, for inputs that fit it."""
    from .summarise import solve_local

    return solve_local(nodes, k, seed, PRACTICAL, restarts)


def kmeans_points(points: DataFrame, k: int, d: int, seed: int = 1, plusplus: bool = True, rounds: int = 10) -> list[list[float]]:
    """k-means++ on points(node_id, coords, weight), or Lloyd's k-means from hash-chosen points."""
    if plusplus:
        return centre_ops.kmeanspp(points, k, d, seed, rounds, F.col("weight"))
    start = points.select("coords", portable_uniform(seed, "node_id", 0).alias("u"), "node_id").orderBy("u", "node_id").limit(k).collect()
    return centre_ops.lloyd(points, [list(x["coords"]) for x in start], d, rounds, means=True, weight=F.col("weight"))[0]


def kmeans_library(points: DataFrame, k: int, seed: int = 1) -> np.ndarray:
    """Cross-check by Spark's own KMeans."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    model = KMeans(k=k, seed=seed, weightCol="weight", initMode="k-means||").fit(points.select(array_to_vector("coords").alias("features"), "weight"))
    return np.array(model.clusterCenters())


def node_points(nodes: DataFrame) -> DataFrame:
    """Every realisation as a point of weight w p."""
    return unpack(nodes).select(F.col("loc_id").alias("node_id"), "coords", (F.col("weight") * F.col("prob")).alias("weight"))


def _points(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    coords = batch.column("coords")
    d = len(coords.flatten()) // max(len(coords), 1)
    return coords.flatten().to_numpy(zero_copy_only=False).reshape(-1, max(d, 1)), batch.column("weight").to_numpy(zero_copy_only=False)


def _rows(x: np.ndarray, w: np.ndarray) -> pa.RecordBatch:
    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x).ravel()))
    return pa.record_batch({"coords": lists, "weight": pa.array(w)})


def _seed_reduce(x: np.ndarray, w: np.ndarray, size: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """Squared-distance seeds, each with the weight of the points nearest to it."""
    if len(x) <= size:
        return x, w
    at = kernels.seed_points(x, w, size, rng, 2, uniform_first=False)
    near = np.zeros(len(x), int)
    best = np.full(len(x), np.inf)
    for j, c in enumerate(at):
        gap = ((x - x[c]) ** 2).sum(1)
        near, best = np.where(gap < best, j, near), np.minimum(gap, best)
    return x[at], np.bincount(near, w, len(at))


def stream_kmeanspp(points: DataFrame, k: int, seed: int = 1, size: int = 0) -> tuple[np.ndarray, int]:
    """Merge-and-reduce coreset of points by seeding, in every partition, then k-means++ on the union; (centres, coreset rows)."""
    size = size or 200 * k

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng(seed)
        levels: list = []
        for batch in batches:
            for at in range(0, batch.num_rows, size):
                x, w = _points(batch.slice(at, size))
                j = 0
                while j < len(levels) and levels[j] is not None:
                    x, w = _seed_reduce(np.r_[levels[j][0], x], np.r_[levels[j][1], w], size, rng)
                    levels[j] = None
                    j += 1
                if j == len(levels):
                    levels.append(None)
                levels[j] = x, w
        parts = [x for x in levels if x is not None]
        if parts:
            yield _rows(*_seed_reduce(np.concatenate([x for x, _ in parts]), np.concatenate([w for _, w in parts]), size, rng))

    found = points.select("coords", "weight").mapInArrow(run, POINT)
    return _solved_points(found, k, seed, size)


def _solved_points(parts: DataFrame, k: int, seed: int, size: int) -> tuple[np.ndarray, int]:
    """Partition coresets are merged by a tree of tasks until one is left, then k-means++ on it."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, w, rng = None, None, np.random.default_rng(seed)
        for batch in batches:
            if batch.num_rows:
                own = _points(batch)
                x, w = own if x is None else _seed_reduce(np.r_[x, own[0]], np.r_[w, own[1]], size, rng)
        if x is not None:
            yield _rows(x, w)

    width = parts.rdd.getNumPartitions()
    while width > 1:
        width = -(-width // 16)
        parts = kept(parts.coalesce(width).mapInArrow(merge, POINT))
    rows = parts.orderBy("coords").collect()  # at most `size` rows
    if not rows:
        return np.zeros((0, 0)), 0
    x, w = np.array([r["coords"] for r in rows]), np.array([r["weight"] for r in rows])
    return kernels.kmeans(x, w, k, seed), len(x)


class FeatureTree:
    """One-pass tree of additive cluster features (count, sum, sum of squares) with a reference point each.

    A feature of level j takes points within radius T / 2^j of its reference if its squared error stays below the
    threshold; else the point goes to its children.  Beyond the budget the threshold doubles and the features are inserted again.
    """

    def __init__(self, budget: int, depth: int = 8):
        self.budget, self.depth, self.threshold, self.features = budget, depth, 0.0, []

    def clear(self) -> None:
        self.features, self.children = [], {(): []}

    def insert(self, n: np.ndarray, s: np.ndarray, q: np.ndarray) -> None:
        """A batch of features (count, sum, sum of squares), in order; the tree is rebuilt once it is beyond the budget."""
        if not self.features:
            self.clear()
        self._place((), 0, np.arange(len(n)), s / n[:, None], n, s, q)
        if len(self.features) > self.budget:
            self.rebuild()

    def _place(self, path: tuple, level: int, rows: np.ndarray, at: np.ndarray, n: np.ndarray, s: np.ndarray, q: np.ndarray) -> None:
        own = self.children.setdefault(path, [])
        radius = np.sqrt(self.threshold) * 4 / 2**level
        near, gap = np.full(len(rows), -1), np.full(len(rows), np.inf)
        if own:
            found = kernels.distances(at[rows], np.array([self.features[j][3] for j in own]))
            near, gap = np.array(own)[found.argmin(1)], found.min(1)
        while (gap > radius).any():  # the first point that no feature is near to becomes one, for those behind it too
            first = int((gap > radius).argmax())
            row = rows[first]
            own.append(len(self.features))
            self.features.append([float(n[row]), s[row].copy(), float(q[row]), at[row]])
            later = np.arange(len(rows)) > first
            rows, near, gap = (np.r_[x[:first], x[first + 1 :]] for x in (rows, near, gap))
            later = np.delete(later, first)
            to = np.sqrt(((at[rows] - at[row]) ** 2).sum(1))
            closer = later & (to < gap)
            near[closer], gap[closer] = own[-1], to[closer]
        for j in np.unique(near).tolist():
            members, f = rows[near == j], self.features[j]
            m, t, r = f[0] + np.cumsum(n[members]), f[1] + np.cumsum(s[members], 0), f[2] + np.cumsum(q[members])
            fits = r - (t * t).sum(1) / m <= self.threshold
            taken = len(members) if level == self.depth - 1 or fits.all() else int(fits.argmin())
            if taken:
                f[0], f[1], f[2] = float(m[taken - 1]), t[taken - 1], float(r[taken - 1])
            if taken < len(members):
                self._place((*path, j), level + 1, members[taken:], at, n, s, q)

    def rebuild(self) -> None:
        old = self.features
        while len(old) > self.budget:
            if not self.threshold:
                refs = np.array([f[3] for f in old[:256]])
                gaps = kernels.distances(refs, refs)
                self.threshold = float(np.median(np.sort(gaps, 1)[:, 1]) ** 2) or 1e-12
            self.threshold *= 2
            self.clear()
            self._place((), 0, np.arange(len(old)), np.array([f[1] / f[0] for f in old]), *(np.array([f[k] for f in old]) for k in range(3)))
            old = self.features


def feature_tree(points: DataFrame, k: int, seed: int = 1, budget: int = 0) -> tuple[np.ndarray, int]:
    """The tree in every partition, its centroids merged by seeding, then k-means++; (centres, coreset rows)."""
    budget = budget or 200 * k

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = FeatureTree(budget)
        for batch in batches:
            x, w = _points(batch)
            x, w = x[w > 0], w[w > 0]
            for at in range(0, len(x), 512):
                own, weight = x[at : at + 512], w[at : at + 512]
                tree.insert(weight, weight[:, None] * own, weight * (own * own).sum(1))
        if tree.features:
            n = np.array([f[0] for f in tree.features])
            yield _rows(np.array([f[1] for f in tree.features]) / n[:, None], n)

    return _solved_points(points.select("coords", "weight").mapInArrow(run, POINT), k, seed, budget)


def cluster_features(points: DataFrame, by: str, d: int, weight: str = "weight") -> DataFrame:
    """Additive features of each group: n, s0..s{d-1}, q; they add up over any split of the group."""
    w = F.col(weight)
    square = F.aggregate("coords", F.lit(0.0), lambda s, x: s + x * x)
    return points.groupBy(by).agg(F.sum(w).alias("n"), *(F.sum(w * F.get("coords", F.lit(i))).alias(f"s{i}") for i in range(d)), F.sum(w * square).alias("q"))


def collapse_medians(nodes: DataFrame, medians: DataFrame, k: int, d: int, seed: int = 1) -> list[list[float]]:
    """Every node becomes its median with weight w p, then deterministic k-median."""
    points = medians.select("node_id", "coords", (F.col("weight") * F.col("mass")).alias("weight"))
    return centre_ops.kmedian_lloyd(points, k, d, seed, weight=F.col("weight"))


def collapse_means(nodes: DataFrame, k: int, d: int, seed: int = 1) -> list[list[float]]:
    """Every node becomes its expected location, then k-means++."""
    real = unpack(nodes)
    y = group_centroids(real, "node_id", F.col("prob"), d)
    points = y.join(nodes.select("node_id", (F.col("weight") * F.col("mass")).alias("weight")), "node_id").withColumnRenamed("y", "coords")
    return centre_ops.kmeanspp(points, k, d, seed, weight=F.col("weight"))


def uniform_sample(nodes: DataFrame, size: int, seed: int = 1) -> DataFrame:
    """A hash sample of about `size` nodes, weights scaled by n / taken: the summary without cells."""
    n = nodes.count()
    taken = nodes.where(portable_uniform(seed, "node_id", F.lit("uniform")) < size / max(n, 1))
    m = taken.count()
    return taken.withColumn("weight", F.col("weight") * F.lit(n / max(m, 1)))


