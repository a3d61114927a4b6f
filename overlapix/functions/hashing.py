"""Hash families that Spark, NumPy and SQL compute alike.

``poly`` and ``affine`` map a 31-bit fingerprint with integer arithmetic below
2**62; ``xx64`` mixes 64 bits and is the family for production, where hash
values of different elements must practically never meet.
"""

from __future__ import annotations

import random
from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2**31 - 1
#: Quantile cells of the Gaussian that projections read, and its fixed-point unit.
CELLS, UNIT = 4096, 65536
FAMILIES = ("poly", "affine", "xx64")
PAD_A, PAD_B, AUX = "pA:", "pB:", "aux:"


def fp(token: Column) -> Column:
    """31-bit fingerprint of a string, the same in every engine that has md5."""
    return F.conv(F.substring(F.md5(token.cast("binary")), 1, 15), 16, 10).cast("bigint") % P


def fp64(token: Column) -> Column:
    """64-bit fingerprint for production."""
    return F.xxhash64(token)


def py_fp(token: str) -> int:
    import hashlib

    return int(hashlib.md5(token.encode()).hexdigest()[:15], 16) % P


@lru_cache(maxsize=64)
def draws(h: int, seed: int) -> tuple[tuple[int, int, int, int, int, float], ...]:
    """Per hash: five integers and a uniform offset, all from ``seed``."""
    rng = random.Random(seed)
    return tuple((rng.randrange(1, P), rng.randrange(P), rng.randrange(1, P), rng.randrange(P), rng.randrange(1, P), rng.random()) for _ in range(h))


def hash_values(x: np.ndarray, draw: tuple, family: str) -> np.ndarray:
    """One hash of every element."""
    a, b, c, d, g = (np.uint64(v) for v in draw[:5])
    x = x.astype(np.uint64)
    if family == "xx64":
        y = (x ^ (a << np.uint64(32) | b)) * np.uint64(0x9E3779B97F4A7C15)
        y ^= y >> np.uint64(29)
        y *= (c << np.uint64(32) | d) | np.uint64(1)
        y ^= y >> np.uint64(32)
        y *= np.uint64(0xD6E8FEB86659FD93)
        return ((y ^ y >> np.uint64(32)) >> np.uint64(1)).astype(np.int64)
    p = np.uint64(P)
    y = (a * x + b) % p
    if family == "affine":
        return y.astype(np.int64)
    y = y * y % p
    y = (c * y + d + x) % p
    y = y * y % p
    return ((g * y + (c * x) % p) % p).astype(np.int64)


@lru_cache(maxsize=1)
def gaussian_cells() -> tuple[int, ...]:
    """Quantiles of the standard normal at the cells' middles, in fixed point."""
    normal = NormalDist()
    return tuple(round(normal.inv_cdf((i + 0.5) / CELLS) * UNIT) for i in range(CELLS))


def gaussian(values: np.ndarray) -> np.ndarray:
    return np.array(gaussian_cells(), np.int64)[values % CELLS]
