"""The data-side and query-side maps of each scheme, written out.

Signatures never need these rows; tests and the identities do.
"""

from __future__ import annotations

from decimal import ROUND_HALF_UP, Decimal

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from overlapix.functions.hashing import PAD_A, PAD_B, fp


def _pads(block: str, n: Column) -> Column:
    some = F.transform(F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0))), lambda i: fp(F.concat(F.lit(block), i.cast("string"))))
    return F.when(n > 0, some).otherwise(F.array().cast("array<bigint>"))


def _padded(sets: DataFrame, m: int, block: str) -> DataFrame:
    """A set larger than ``m`` gets no pads and is flagged."""
    made = sets.withColumn("elems", F.concat("elems", _pads(block, F.lit(m) - F.col("f"))))
    return made.withColumn("over", F.col("f") > m).withColumn("padded_f", F.size("elems"))


def pad_data_one(sets: DataFrame, m: int) -> DataFrame:
    """Every data set filled up to ``m`` elements of its own block."""
    return _padded(sets, m, PAD_A)


def pad_query_none(sets: DataFrame) -> DataFrame:
    return sets.withColumn("over", F.lit(False)).withColumn("padded_f", F.col("f"))


def pad_two_sided(sets: DataFrame, m: int, side: str) -> DataFrame:
    """Each side filled from a block that the other never has."""
    return _padded(sets, m, PAD_A if side == "data" else PAD_B)


def pad_weighted(sets: DataFrame, m: int, side: str) -> DataFrame:
    """``elems, weights``: ones, and one coordinate of weight M - f."""
    return pad_weighted_real(sets.select("id", "elems", F.transform("elems", lambda e: F.lit(1.0)).alias("weights")), float(m), side)


def pad_weighted_real(weighted: DataFrame, m: float, side: str) -> DataFrame:
    """The same for any weights; ``m`` bounds their sum."""
    own = fp(F.lit("weight:A" if side == "data" else "weight:B"))
    rest = F.greatest(F.lit(m) - F.aggregate("weights", F.lit(0.0), lambda a, w: a + w), F.lit(0.0))
    return weighted.select("id", F.concat("elems", F.array(own)).alias("elems"), F.concat("weights", F.array(rest)).alias("weights"))


def _powers(f: Column, z: float, m: int) -> list[Column]:
    out, x = [], f * F.lit(z)
    for _ in range(m):
        out.append(x)
        x = x * x
    return out


def augment_l2(sets: DataFrame, u: float, v: float, m: int, side: str) -> DataFrame:
    """``aug``: 2m scalars after the coordinates, which weigh ``u / v`` each."""
    powers, halves = _powers(F.col("f"), (u / v) * (u / v), m), [F.lit(0.5)] * m
    return sets.withColumn("aug", F.array(*(powers + halves if side == "data" else halves + powers)))


def augment_sign(sets: DataFrame, u: float, v: float, m: int, side: str) -> DataFrame:
    powers, zeros = [F.lit(0.5) - p for p in _powers(F.col("f"), (u / v) * (u / v), m)], [F.lit(0.0)] * m
    return sets.withColumn("aug", F.array(*(powers + zeros if side == "data" else zeros + powers)))


def augment_norm(sets: DataFrame, v: float, side: str) -> DataFrame:
    """Completes the norm to one, on coordinates that the sides do not share."""
    rest = F.sqrt(F.greatest(F.lit(0.0), 1 - F.col("f") / F.lit(v * v)))
    return sets.withColumn("aug", F.array(rest, F.lit(0.0)) if side == "data" else F.array(F.lit(0.0), rest))


def augmented_product(a: Column | np.ndarray, scale: float, x: Column | np.ndarray, q: Column | np.ndarray, n: int) -> Column | np.ndarray:
    """Inner product of two augmented vectors, from the overlap and the ``n`` scalars;
    of columns, or of arrays with a row a scalar."""
    return a * (scale * scale) + _total([x[i] * q[i] for i in range(n)])


def augmented_norm2(f: Column, scale: float, aug: Column, n: int) -> Column:
    return f * F.lit(scale * scale) + _total([aug[i] * aug[i] for i in range(n)])


def rounded(values: np.ndarray, places: int = 6) -> np.ndarray:
    """What ``F.round`` gives: the shortest decimal form of a number, halves away from zero.
    Only numbers next to a half need that form written out."""
    whole = np.abs(values) * 10.0**places
    out = np.copysign(np.floor(whole + 0.5) / 10.0**places, values)
    for i in np.flatnonzero(~(np.abs(whole - np.floor(whole) - 0.5) > 1e-4) | (whole > 1e9)):
        if np.isfinite(values[i]):
            out[i] = float(Decimal(repr(float(values[i]))).quantize(Decimal(1).scaleb(-places), ROUND_HALF_UP))
        else:
            out[i] = values[i]
    return out


def _total(parts: list) -> Column | np.ndarray:
    out = 0.0
    for p in parts:
        out = out + p
    return out


def weighted_pairs(x: DataFrame, q: DataFrame) -> DataFrame:
    """``q_id, x_id, low, high``: sums of minima and maxima of pairs that share an element."""
    lx = x.select(F.col("id").alias("x_id"), F.explode(F.arrays_zip("elems", "weights")).alias("p")).select("x_id", F.col("p.elems").alias("e"), F.col("p.weights").alias("wx"))
    lq = q.select(F.col("id").alias("q_id"), F.explode(F.arrays_zip("elems", "weights")).alias("p")).select("q_id", F.col("p.elems").alias("e"), F.col("p.weights").alias("wq"))
    low = lx.join(lq, "e").groupBy("q_id", "x_id").agg(F.sum(F.least("wx", "wq")).alias("low"))
    sx, sq = lx.groupBy("x_id").agg(F.sum("wx").alias("sx")), lq.groupBy("q_id").agg(F.sum("wq").alias("sq"))
    return low.join(sx, "x_id").join(F.broadcast(sq), "q_id").select("q_id", "x_id", "low", (F.col("sx") + F.col("sq") - F.col("low")).alias("high"))
