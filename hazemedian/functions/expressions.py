"""Column expressions: distances, nearest centres, portable uniforms, power-of-two classes."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Up to this dimension a distance is unrolled, so that it stays inside whole-stage code generation.
WIDE = 32


def column(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def point(values: Sequence[float]) -> Column:
    return F.array(*(F.lit(float(v)) for v in values))


def squared_distance(a: Column | str, b: Column | str, d: int) -> Column:
    a, b = column(a), column(b)
    if d <= WIDE:
        return reduce(lambda x, y: x + y, (F.pow(F.get(a, F.lit(i)) - F.get(b, F.lit(i)), F.lit(2.0)) for i in range(d)))
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def distance(a: Column | str, b: Column | str, d: int) -> Column:
    return F.sqrt(squared_distance(a, b, d))


def centre_array(centres: Sequence[Sequence[float]]) -> Column:
    """All centres as one literal: k points of d numbers, a model of fixed size that travels with the plan."""
    return F.array(*(point(c) for c in centres))


def nearest(coords: Column | str, centres: Sequence[Sequence[float]], d: int, places: int | None = None) -> Column:
    """struct(dist, centre) of the nearest centre, the lowest index on ties; no join and no shuffle.

    With `places` the comparison is on rounded distances, which two engines agree on.
    """
    gap = lambda c: distance(coords, c, d)
    if places is not None:
        gap = lambda c: F.round(distance(coords, c, d), places)
    return F.array_min(F.transform(centre_array(centres), lambda c, i: F.struct(gap(c).alias("dist"), i.cast("int").alias("centre"))))


def portable_uniform(seed: int | Column, name: Column | str, draw: int | Column = 0) -> Column:
    """A uniform in [0, 1) of (seed, name, draw) that any engine with md5 computes alike."""
    lit = lambda v: v if isinstance(v, Column) else F.lit(v)
    text = F.concat_ws(":", lit(seed).cast("string"), column(name).cast("string"), lit(draw).cast("string"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def power_class(value: Column | str, radius: Column | float, closed_low: bool) -> Column:
    """0 below the radius, h from 2^(h-1) radius: by comparisons with exact powers of two; a logarithm only tells which three to try.

    closed_low: the edge 2^(h-1) R belongs to class h (open balls); otherwise to h - 1.
    """
    value, radius = column(value), radius if isinstance(radius, Column) else F.lit(float(radius))
    above = (lambda edge: value >= edge) if closed_low else (lambda edge: value > edge)
    first = F.greatest(F.coalesce(F.floor(F.log2(F.when(value > 0, value) / radius)).cast("int"), F.lit(0)) - 1, F.lit(0))
    counted = sum((above(radius * F.pow(F.lit(2.0), first + h)).cast("int") for h in range(3)), first)
    return F.when(radius <= 0, 0).otherwise(counted)


def vector_sum(d: int, value) -> list[Column]:
    """Aggregates g0..g{d-1}: the sums of value(i)."""
    return [F.sum(value(i)).alias(f"g{i}") for i in range(d)]


def gathered(d: int, divide_by: Column | str | None = None) -> Column:
    parts = [F.col(f"g{i}") for i in range(d)]
    return F.array(*(p / column(divide_by) for p in parts) if divide_by is not None else parts)
