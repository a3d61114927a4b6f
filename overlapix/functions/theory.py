"""Collision laws, exponents and plans: plain floats, with a Column twin where curves are frames."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def phi(x: float) -> float:
    return 0.5 * math.erfc(-x / math.sqrt(2))


def f_r(d: float, r: float) -> float:
    """Collision of two points at distance ``d`` under cells of width ``r``; 1 at distance 0."""
    if d <= 0:
        return 1.0
    return 1 - 2 * phi(-r / d) - 2 * d / (r * math.sqrt(2 * math.pi)) * (1 - math.exp(-(r * r) / (2 * d * d)))


def srp(cos: float) -> float:
    return 1 - math.acos(max(-1.0, min(1.0, cos))) / math.pi


def minhash(a: float, fx: float, fq: float) -> float:
    return a / (fx + fq - a)


def sampling(a: float, fx: float, fy: float, d: float, n: float, miss_range: str = "zero_to_n_minus_1") -> float:
    """Collision of coordinate sampling.  With misses drawn from 1..n a hit meets no
    miss; with misses from 0..n-1 the law depends on the overlap alone."""
    quiet = d - (fx + fy - a) if miss_range == "one_to_n" else d - a
    return a / d + quiet / d / n


def opm1(a: float, fq: float, m: float) -> float:
    return a / (m + fq - a)


def opm2(a: float, m: float) -> float:
    return a / (2 * m - a)


def rho(p1: float, p2: float) -> float | None:
    """Query exponent; None where a probability is not strictly between 0 and 1."""
    return math.log(p1) / math.log(p2) if 0 < p1 < 1 and 0 < p2 < 1 else None


def rho_opm(s: float, c: float) -> float | None:
    return rho(s / (2 - s), c * s / (2 - c * s))


def rho_sign(s: float, c: float) -> float | None:
    return rho(srp(s), srp(c * s))


def rho_opm_q(s0: float, c: float, fq: float, m: float) -> float | None:
    return rho(opm1(s0, fq, m), opm1(c * s0, fq, m))


def rho_minhash_q(s0: float, c: float, fq: float, m: float) -> float | None:
    """Undefined where the far point may contain the whole query."""
    return rho(s0 / (fq + m - s0), c * s0 / fq) if c * s0 < fq else None


def rho_sampling(s0: float, c: float, d: float, n: float) -> float | None:
    return rho(sampling(s0, 0, 0, d, n), sampling(c * s0, 0, 0, d, n))


def rho_l2alsh(s: float, c: float, ms=(1, 2, 3, 4, 5), us=None, rs=None) -> tuple[float, int, float, float] | None:
    """Best exponent of the padded-distance scheme for threshold ``s`` = S0 over the
    squared largest norm, over a grid of (m, U, r); with what attains it."""
    us = us or [round(0.3 + 0.02 * i, 2) for i in range(35)]
    rs = rs or [0.5 + 0.25 * i for i in range(19)]
    best = None
    for m in ms:
        for u in us:
            if u >= 1 or u ** (2 ** (m + 1) - 2) / s >= 1 - c:
                continue
            near = math.sqrt(max(0.0, m / 2 - 2 * s * u * u + 2 * u ** 2 ** (m + 1)))
            far = math.sqrt(max(0.0, m / 2 - 2 * c * s * u * u))
            for r in rs:
                x = rho(f_r(near, r), f_r(far, r))
                if x is not None and (best is None or x < best[0]):
                    best = (x, m, u, r)
    return best


def rho_signalsh(s: float, c: float, ms=(1, 2, 3, 4, 5), us=None, printed: bool = False) -> tuple[float, int, float] | None:
    """Best exponent of the padded-sign scheme.  The far end's cosine is normalised
    by its norms' lower bound unless ``printed`` asks for the shorter form."""
    us = us or [round(0.3 + 0.02 * i, 2) for i in range(35)]
    best = None
    for m in ms:
        peak = (m / (4 * (2**m - 1))) ** (2.0**-m)
        for u in us:
            if u >= 1:
                continue
            z = s * u * u
            y = min(c * z, peak)
            x = rho(srp(z / (m / 4 + u ** 2 ** (m + 1))), srp(y if printed else y / (m / 4 + y ** 2**m)))
            if x is not None and (best is None or x < best[0]):
                best = (x, m, u)
    return best


def plan_kl(n: int, p1: float, p2: float, delta: float = 0.1) -> tuple[int, int]:
    """Hashes a table and tables for n points and failure probability delta."""
    k = max(1, math.ceil(math.log(n) / -math.log(p2)))
    return k, max(1, math.ceil(math.log(1 / delta) / p1**k))


def candidate_probability(p: float, k: int, l: int) -> float:  # noqa: E741
    return 1 - (1 - p**k) ** l


def cost(n: float, r: float, p2: float) -> tuple[float, float]:
    """(query cost, space) up to constants: n^rho log n over log 1/p2, and n^(1+rho)."""
    return n**r * math.log(n) / -math.log(p2), n ** (1 + r)


# Column forms


def rho_col(p1: Column, p2: Column) -> Column:
    ok = (p1 > 0) & (p1 < 1) & (p2 > 0) & (p2 < 1)
    return F.when(ok, F.log(p1) / F.log(p2))


def srp_col(cos: Column) -> Column:
    return 1 - F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cos))) / F.lit(math.pi)


def opm_col(a: Column, whole: Column) -> Column:
    return a / (whole - a)
