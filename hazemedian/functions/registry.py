"""SQL names of the scalar functions, aggregates and table functions."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..kernels import Block, iterative_medians, reduce_block
from ..model import PRACTICAL


class LadderLevels:
    """Levels of a ladder after n nodes: (level, nodes it stands for)."""

    def eval(self, n: int, capacity: int):
        yield 0, n % capacity
        full, level = n // capacity, 1
        while full:
            if full & 1:
                yield level, capacity << (level - 1)
            full, level = full >> 1, level + 1


class RingEdges:
    """(class, low, high) of the rings round a centre."""

    def eval(self, radius: float, classes: int):
        yield 0, 0.0, radius
        for h in range(1, classes):
            yield h, radius * 2.0 ** (h - 1), radius * 2.0**h


class DrawPoints:
    """(draw, u) of s portable uniforms."""

    def eval(self, draws: int, seed: int):
        from hashlib import md5

        for t in range(1, draws + 1):
            yield t, int(md5(f"{seed}:draw:{t}".encode()).hexdigest()[:8], 16) / 4294967296.0


# Types as objects: workers import this module, and only a session can read a type's name.
@F.pandas_udf(T.ArrayType(T.DoubleType()))
def node_median(coords: pd.Series, prob: pd.Series) -> pd.Series:
    """The node median (two or more updates by the step-ratio rule) of packed coords and probabilities."""
    counts = coords.map(len).to_numpy()
    if not len(counts):
        return pd.Series([], dtype=object)
    x = np.array([p for row in coords for p in row], float)
    y, _, _ = iterative_medians(x, np.concatenate([np.asarray(p, float) for p in prob]), np.r_[0, np.cumsum(counts)])
    return pd.Series(list(map(list, y)))


@F.pandas_udf(T.DoubleType())
def weighted_median_1d(value: pd.Series, weight: pd.Series) -> float:
    """Grouped aggregate: the exact weighted median on a line."""
    order = np.argsort(value.to_numpy(), kind="stable")
    w = weight.to_numpy()[order]
    return float(value.to_numpy()[order][np.searchsorted(np.cumsum(w), w.sum() / 2)]) if len(w) else float("nan")


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def weighted_centroid(coords: pd.Series, weight: pd.Series) -> list:
    """Grouped aggregate: the centre of gravity of weighted points; empty without weight."""
    w = weight.to_numpy(float)
    return (np.stack(coords.to_numpy()).astype(float) * w[:, None]).sum(0) / w.sum() if len(w) and w.sum() > 0 else np.zeros(0)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def summarise_agg(node_id: pd.Series, weight: pd.Series, coords: pd.Series, prob: pd.Series, k: pd.Series, per_k: pd.Series) -> list:
    """Grouped aggregate: a summary of a bounded group of nodes as id, weight, id, weight, ... of the chosen ones."""
    order = np.argsort(node_id.to_numpy(), kind="stable")
    counts = coords.map(len).to_numpy()[order]
    x = np.array([p for i in order for p in coords.iloc[i]], float)
    p = np.concatenate([np.asarray(prob.iloc[i], float) for i in order])
    offsets = np.r_[0, np.cumsum(counts)]
    block = Block(node_id.to_numpy()[order], weight.to_numpy(float)[order], np.add.reduceat(p, offsets[:-1]), offsets, np.arange(len(x)), x, p)
    out = reduce_block(block, int(k.iloc[0]), replace(PRACTICAL, per_k=int(per_k.iloc[0])), 1)
    return np.stack([out.node_id.astype(float), out.weight], 1).ravel()


def register(spark: SparkSession) -> None:
    """Makes everything callable from SQL in this session."""
    spark.udf.register("weighted_centroid", weighted_centroid)
    spark.udf.register("summarise_agg", summarise_agg)
    spark.udtf.register("ladder_levels", F.udtf(LadderLevels, returnType="level: int, nodes: bigint"))
    spark.udtf.register("ring_edges", F.udtf(RingEdges, returnType="class: int, low: double, high: double"))
    spark.udtf.register("draw_points", F.udtf(DrawPoints, returnType="draw: int, u: double"))
    spark.udf.register("node_median", node_median)
    spark.udf.register("weighted_median_1d", weighted_median_1d)
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION point_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE
        RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))""")
    # A node is given by the arrays of its locations and their chances.
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION node_distance(x ARRAY<ARRAY<DOUBLE>>, p ARRAY<DOUBLE>, c ARRAY<DOUBLE>) RETURNS DOUBLE
        RETURN aggregate(zip_with(x, p, (a, w) -> w * sqrt(aggregate(zip_with(a, c, (u, v) -> (u - v) * (u - v)), 0D, (s, t) -> s + t))), 0D, (s, t) -> s + t)""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION node_spread(x ARRAY<ARRAY<DOUBLE>>, p ARRAY<DOUBLE>, y ARRAY<DOUBLE>) RETURNS DOUBLE
        RETURN node_distance(x, p, y) / aggregate(p, 0D, (s, t) -> s + t)""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION assigned_cost(w DOUBLE, x ARRAY<ARRAY<DOUBLE>>, p ARRAY<DOUBLE>, centres ARRAY<ARRAY<DOUBLE>>) RETURNS DOUBLE
        RETURN w * array_min(transform(centres, c -> aggregate(zip_with(x, p, (a, q) -> q * sqrt(aggregate(zip_with(a, c, (u, v) -> (u - v) * (u - v)), 0D, (s, t) -> s + t))), 0D, (s, t) -> s + t)))""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION portable_uniform(seed BIGINT, name STRING, draw BIGINT) RETURNS DOUBLE
        RETURN CAST(conv(substring(md5(concat_ws(':', CAST(seed AS STRING), name, CAST(draw AS STRING))), 1, 8), 16, 10) AS BIGINT) / 4294967296D""")
