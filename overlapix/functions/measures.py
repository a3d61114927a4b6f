"""Similarity of two sets as Column expressions of sizes and overlap."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _ratio(top: Column, bottom: Column) -> Column:
    return F.when(bottom > 0, top / bottom)


def overlap(x: Column, y: Column) -> Column:
    return F.size(F.array_intersect(x, y))


def resemblance(a: Column, fx: Column, fy: Column) -> Column:
    return _ratio(a, fx + fy - a)


def containment(a: Column, f: Column) -> Column:
    """Null for an empty set."""
    return _ratio(a, f)


def cosine_sets(a: Column, fx: Column, fy: Column) -> Column:
    return _ratio(a, F.sqrt(fx.cast("double") * fy))


def hamming(a: Column, fx: Column, fy: Column) -> Column:
    return fx + fy - 2 * a


def sim_opm1(a: Column, fq: Column, m: Column | int) -> Column:
    """Resemblance after data sets are padded to ``m``."""
    return _ratio(a, F.lit(m) + fq - a if isinstance(m, int) else m + fq - a)


def sim_opm2(a: Column, m: Column | int) -> Column:
    """Resemblance after both sides are padded to ``m``."""
    m = F.lit(m) if isinstance(m, int) else m
    return _ratio(a, 2 * m - a)


def as_distance(sim: Column) -> Column:
    return 1 - sim


def resemblance_bounds(a: Column, fq: Column, m: Column | int) -> tuple[Column, Column]:
    """What the resemblance of a set of at most ``m`` elements lies between."""
    return sim_opm1(a, fq, m), containment(a, fq)


def resemblance3(x: Column, y: Column, z: Column) -> Column:
    return _ratio(F.size(F.array_intersect(F.array_intersect(x, y), z)), F.size(F.array_union(F.array_union(x, y), z)))


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)


def norm(x: Column) -> Column:
    return F.sqrt(dot(x, x))


def cosine(x: Column, y: Column) -> Column:
    return _ratio(dot(x, y), norm(x) * norm(y))


def l2(x: Column, y: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(x, y, lambda a, b: F.pow(a.cast("double") - b.cast("double"), F.lit(2.0))), F.lit(0.0), lambda s, v: s + v))
