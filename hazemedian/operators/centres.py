"""Candidate centres of weighted points as DataFrame loops: seeding, medians, means, bicriteria sets.

Each seed and each round is one job over the points with k centres as a literal in the plan; the driver holds k rows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..functions.expressions import centre_array, distance, nearest, portable_uniform, squared_distance
from ..model import PRACTICAL, Profile
from .medians import group_centroids, group_updates

#: Distances are summed as whole numbers of this fraction, so that prefix sums are exact in any order.
SCALE = 1_000_000
RANGES = 4096
#: Points of a range that are sorted for the end of a draw.
FEW_POINTS = 10_000


def first_centre(points: DataFrame, seed: int, key: str = "node_id") -> list:
    """A uniform point: the least portable uniform, then the least key."""
    row = points.select(F.struct(portable_uniform(seed, key, 0).alias("u"), F.col(key).alias("k"), "coords").alias("s")).agg(F.min("s").alias("s")).first()["s"]
    return [row["k"], list(row["coords"])]


def prefix_pick(points: DataFrame, mass: Column, u: float, key: str = "node_id") -> list | None:
    """The first point in key order whose running sum of whole-number masses exceeds u times the total.

    Sums of RANGES equal ranges of the keys come to the driver, the range with the hit is cut again until it holds few
    points, and only these are sorted: no task sees a run of unknown length, however the keys lie.
    """
    rows = points.select(F.col(key).alias("k"), "coords", mass.cast("long").alias("m"))
    low, high = rows.agg(F.min("k"), F.max("k")).first()
    if low is None:
        return None
    before, goal = 0, None
    while True:
        width = (high - low) // RANGES + 1
        inside = rows.where(F.col("k").between(low, high))
        place = F.floor((F.col("k").cast("decimal(38,0)") - F.lit(low)) / F.lit(width)).cast("long")
        runs = sorted(inside.groupBy(place.alias("b")).agg(F.sum("m").alias("m"), F.count("*").alias("n")).collect())
        if goal is None:
            total = sum(x["m"] for x in runs)
            if not total:
                return None
            goal = total * u
        for hit in runs:
            if before + hit["m"] > goal:
                break
            before += hit["m"]
        low, high = low + hit["b"] * width, min(high, low + (hit["b"] + 1) * width - 1)
        if hit["n"] <= FEW_POINTS or width == 1:
            break
    for row in rows.where(F.col("k").between(low, high)).select("k", "m").orderBy("k").toLocalIterator():
        before += row["m"]
        if before > goal:
            break
    return [row["k"], list(rows.where(F.col("k") == row["k"]).select("coords").first()["coords"])]


def seed_centres(points: DataFrame, k: int, d: int, power: int = 1, weight: Column | None = None, seed: int = 7, key: str = "node_id") -> list[list]:
    """[key, coords] of up to k centres, drawn by weight times distance^power with portable uniforms."""
    from hashlib import md5

    chosen = [first_centre(points, seed, key)]
    measure = distance if power == 1 else squared_distance
    while len(chosen) < k:
        u = int(md5(f"{seed}:pick:{len(chosen)}".encode()).hexdigest()[:8], 16) / 4294967296.0
        gap = F.array_min(F.transform(centre_array([c for _, c in chosen]), lambda c: measure("coords", c, d)))
        mass = F.round((weight if weight is not None else F.lit(1.0)) * gap * SCALE)
        found = prefix_pick(points, mass, u, key)
        if found is None:  # fewer than k different locations
            break
        chosen.append(found)
    return chosen


def assign_points(points: DataFrame, centres, d: int, places: int = 9) -> DataFrame:
    """Points with `centre` and `dist` of the nearest, lowest index on (rounded) ties: a projection."""
    return points.withColumn("_n", nearest("coords", centres, d, places)).withColumn("centre", F.col("_n.centre")).withColumn("dist", F.col("_n.dist")).drop("_n")


def median_round(assigned: DataFrame, d: int, weight: Column, centres, updates: int = 2) -> list[list[float]]:
    """Each centre's group median after fixed updates from its centre of gravity; empty groups keep their centre."""
    y = group_centroids(assigned, "centre", weight, d)
    for _ in range(updates):
        new = group_updates(assigned, "centre", weight, d, y, broadcast=True).withColumnRenamed("y", "z")
        y = y.join(F.broadcast(new), "centre").select("centre", F.coalesce("z", "y").alias("y"))
    got = {x["centre"]: list(x["y"]) for x in y.collect()}
    return [got.get(i, list(c)) for i, c in enumerate(centres)]


def mean_round(assigned: DataFrame, d: int, weight: Column, centres) -> list[list[float]]:
    got = {x["centre"]: list(x["y"]) for x in group_centroids(assigned, "centre", weight, d).collect()}
    return [got.get(i, list(c)) for i, c in enumerate(centres)]


def lloyd(points: DataFrame, centres, d: int, rounds: int = 10, means: bool = False, weight: Column | None = None, updates: int = 2, key: str = "node_id") -> tuple[list[list[float]], list[int]]:
    """(centres, moved points of each round) from given centres; stops when no point changes its centre."""
    w = weight if weight is not None else F.lit(1.0)
    moved, old = [], None
    for _ in range(rounds):
        now = assign_points(points, centres, d)
        if old is not None:
            n = assign_points(points, old, d).select(key, F.col("centre").alias("was")).join(now, key).where("was <> centre").count()
            moved.append(n)
            if n == 0:
                break
        old, centres = centres, mean_round(now, d, w, centres) if means else median_round(now, d, w, centres, updates)
    return centres, moved


def kmedian_lloyd(points: DataFrame, k: int, d: int, seed: int = 7, rounds: int = 10, weight: Column | None = None) -> list[list[float]]:
    return lloyd(points, [c for _, c in seed_centres(points, k, d, 1, weight, seed)], d, rounds, weight=weight)[0]


def kmeanspp(points: DataFrame, k: int, d: int, seed: int = 7, rounds: int = 10, weight: Column | None = None) -> list[list[float]]:
    return lloyd(points, [c for _, c in seed_centres(points, k, d, 2, weight, seed)], d, rounds, means=True, weight=weight)[0]


def local_points(points: DataFrame, most: int = 2_000_000) -> tuple[np.ndarray, np.ndarray]:
    """A sample of checked size as arrays."""
    rows = points.select("coords", "weight").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} points for a local solver")
    return np.array([x["coords"] for x in rows], float), np.array([x["weight"] for x in rows], float)


def sampled_bicriteria(points: DataFrame, k: int, d: int, seed: int = 7, profile: Profile = PRACTICAL, key: str = "node_id") -> np.ndarray:
    """At most 2k centres: a hash sample of about sqrt(n k log k) points is solved, then the points it serves worst."""
    n = points.count()
    size = min(n, max(4 * k, int(np.ceil(np.sqrt(n * k * max(1.0, np.log(k)))))))
    first = kernels.kmedian_lloyd(*local_points(points.where(portable_uniform(seed, key, F.lit("sample")) <= size / n)), k, seed, profile)
    if size == n:
        return first
    far = points.withColumn("dist", nearest("coords", first.tolist(), d)["dist"])
    worst = min(n, max(2 * k, int(np.ceil(n * k * max(1.0, np.log(k)) / size))))
    # Exactly so many, however many points are equally far: ties go by the hashed key.
    tail = far.orderBy(F.col("dist").desc(), portable_uniform(seed, key, F.lit("tail")), key).limit(worst)
    tail = kernels.kmedian_lloyd(*local_points(tail), k, seed + 1, profile)
    return np.concatenate([first, tail])


def seed_parallel(points: DataFrame, k: int, d: int, seed: int = 7, rounds: int = 5, factor: int = 2, profile: Profile = PRACTICAL, key: str = "node_id") -> np.ndarray:
    """k centres after a few oversampling rounds instead of k passes: each round keeps points by hashed chance, then the kept are weighted and solved."""
    chosen = [first_centre(points, seed, key)[1]]
    for r in range(rounds):
        near = points.withColumn("dist", nearest("coords", chosen, d)["dist"])
        total = near.agg(F.sum("dist")).first()[0]
        if not total:
            break
        chance = F.col("dist") * F.lit(factor * k / total)
        chosen += [list(x["coords"]) for x in near.where(portable_uniform(seed, key, F.lit(f"round{r}")) < chance).select("coords").collect()]
    got = {x["centre"]: x["w"] for x in assign_points(points, chosen, d).groupBy("centre").agg(F.sum("weight").alias("w")).collect()}
    return kernels.kmedian_lloyd(np.array(chosen), np.array([got.get(i, 0.0) for i in range(len(chosen))]), k, seed, profile)
