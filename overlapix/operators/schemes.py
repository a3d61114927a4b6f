"""Hashing schemes: signatures of data and query sets, and their collision laws.

One pass over Arrow batches computes a signature, without a shuffle: element
hashes are reduced per set with NumPy.  Padding is never written out: the pads
of a set of size f are the first M - f of a fixed list, so the least pad hash is
a step function of M - f with about ln M steps (the staircase), and a padded
code is the lesser of the raw code and a step.  Raw code and size are therefore
enough for every M.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapix.functions import hashing as H
from overlapix.functions import theory

SIGNATURE = "id bigint, f int, sig array<bigint>, pad array<boolean>"
CHUNK = 1 << 20


@dataclass(frozen=True)
class Scheme:
    """``kind`` and parameters of a scheme; the functions below do the work."""

    kind: str
    h: int
    seed: int
    family: str = "poly"
    params: dict = field(default_factory=dict, hash=False)

    def __getitem__(self, name: str):
        return self.params[name]

    def with_(self, **params) -> Scheme:
        return replace(self, params={**self.params, **params})

    def data_signatures(self, sets: DataFrame) -> DataFrame:
        return signatures(sets, self, "data")

    def query_signatures(self, sets: DataFrame) -> DataFrame:
        return signatures(sets, self, "query")

    def collision_prob(self, a: float, fx: float, fq: float) -> float:
        return LAWS[self.kind](self, a, fx, fq)

    def rho(self, s0: float, c: float, fx: float, fq: float) -> float | None:
        """Exponent between overlaps ``s0`` and ``c * s0`` at the given sizes."""
        return theory.rho(self.collision_prob(s0, fx, fq), self.collision_prob(c * s0, fx, fq))


def minhash(h: int, seed: int, family: str = "poly") -> Scheme:
    return Scheme("minhash", h, seed, family)


def opm1(h: int, seed: int, m: int, family: str = "poly", explicit: bool = False) -> Scheme:
    return Scheme("opm1", h, seed, family, {"m": m, "explicit": explicit})


def opm2(h: int, seed: int, m: int, family: str = "poly", explicit: bool = False) -> Scheme:
    return Scheme("opm2", h, seed, family, {"m": m, "explicit": explicit})


def srp(h: int, seed: int, family: str = "poly", bits: int = 1) -> Scheme:
    return Scheme("srp" if bits == 1 else "srp2", h, seed, family, {"width": 0.75})


def l2lsh(h: int, seed: int, r: float = 2.5, family: str = "poly") -> Scheme:
    return Scheme("l2lsh", h, seed, family, {"r": r})


def l2_alsh(h: int, seed: int, v: float, u: float = 0.83, m: int = 3, r: float = 2.5, family: str = "poly") -> Scheme:
    return Scheme("l2alsh", h, seed, family, {"v": v, "u": u, "m": m, "r": r})


def sign_alsh(h: int, seed: int, v: float, u: float = 0.75, m: int = 2, family: str = "poly") -> Scheme:
    return Scheme("signalsh", h, seed, family, {"v": v, "u": u, "m": m})


def norm_sign_alsh(h: int, seed: int, v: float, family: str = "poly") -> Scheme:
    return Scheme("normsign", h, seed, family, {"v": v})


def sampling(h: int, seed: int, universe: list[int], n: int, miss_range: str = "zero_to_n_minus_1") -> Scheme:
    return Scheme("sampling", h, seed, "poly", {"universe": tuple(universe), "n": n, "miss_range": miss_range})


def bit_sampling(h: int, seed: int, universe: list[int]) -> Scheme:
    return Scheme("bits", h, seed, "poly", {"universe": tuple(universe)})


def one_permutation(h: int, seed: int, m: int | None = None, family: str = "poly") -> Scheme:
    """One hash, ``h`` bins, empty bins filled from the next full one."""
    return Scheme("oph", h, seed, family, {"m": m})


LAWS: dict[str, Callable[[Scheme, float, float, float], float]] = {
    "minhash": lambda s, a, fx, fq: theory.minhash(a, fx, fq),
    "oph": lambda s, a, fx, fq: theory.minhash(a, fx, fq),
    "opm1": lambda s, a, fx, fq: theory.opm1(a, fq, max(s["m"], fx)),
    "opm2": lambda s, a, fx, fq: a / (max(s["m"], fx) + max(s["m"], fq) - a),
    "opmw": lambda s, a, fx, fq: theory.opm2(a, s["m"]),
    "srp": lambda s, a, fx, fq: theory.srp(a / math.sqrt(fx * fq)),
    "l2lsh": lambda s, a, fx, fq: theory.f_r(math.sqrt(fx + fq - 2 * a), s["r"]),
    "l2alsh": lambda s, a, fx, fq: theory.f_r(l2_distance(s, a, fx, fq), s["r"]),
    "signalsh": lambda s, a, fx, fq: theory.srp(sign_cosine(s, a, fx, fq)),
    "normsign": lambda s, a, fx, fq: theory.srp(a / s["v"] ** 2),
    "sampling": lambda s, a, fx, fq: theory.sampling(a, fx, fq, len(s["universe"]), s["n"], s["miss_range"]),
    "bits": lambda s, a, fx, fq: 1 - (fx + fq - 2 * a) / len(s["universe"]),
}


def l2_distance(s: Scheme, a: float, fx: float, fq: float) -> float:
    z, e = (s["u"] / s["v"]) ** 2, 2 ** s["m"]
    return math.sqrt(max(0.0, s["m"] / 2 - 2 * a * z + (fx * z) ** e + (fq * z) ** e))


def sign_cosine(s: Scheme, a: float, fx: float, fq: float) -> float:
    z, e = (s["u"] / s["v"]) ** 2, 2 ** s["m"]
    return a * z / math.sqrt((s["m"] / 4 + (fx * z) ** e) * (s["m"] / 4 + (fq * z) ** e))


# staircases


def pad_hashes(m: int, draw: tuple, family: str, block: str) -> np.ndarray:
    return H.hash_values(np.array([H.py_fp(f"{block}{i}") for i in range(m)], np.int64), draw, family)


def staircase(h: int, m: int, seed: int, family: str = "poly", block: str = H.PAD_A) -> list[tuple[np.ndarray, np.ndarray]]:
    """Per hash: the numbers of pads at which the least pad hash falls, and the values from there on."""
    base = np.array([H.py_fp(f"{block}{i}") for i in range(m)], np.int64)
    out = []
    for draw in H.draws(h, seed):
        low = np.minimum.accumulate(H.hash_values(base, draw, family)) if m else np.zeros(0, np.int64)
        at = np.flatnonzero(np.diff(low, prepend=low[:1] + 1)) if m else np.zeros(0, np.int64)
        out.append((at + 1, low[at]))
    return out


def staircase_frame(spark, h: int, m: int, seed: int, family: str = "poly", block: str = H.PAD_A) -> DataFrame:
    """``t, m_from, pad_min``."""
    rows = [(t, int(a), int(v)) for t, (at, low) in enumerate(staircase(h, m, seed, family, block)) for a, v in zip(at, low, strict=True)]
    return spark.createDataFrame(rows, "t int, m_from bigint, pad_min bigint")


# signatures


def _sets_of(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """ids, sizes, elements one after another, starts; empty sets are left out."""
    col = batch.column(1)
    sizes = np.diff(col.offsets.to_numpy())
    ids = batch.column(0).to_numpy(zero_copy_only=False)
    flat = col.flatten().to_numpy(zero_copy_only=False)
    keep = sizes > 0
    sizes = sizes[keep]
    return ids[keep], sizes, flat, np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(np.int64)


def runner(scheme: Scheme, side: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """What makes signatures of batches ``id, elems``, for use inside a task."""
    if scheme.kind in ("cws", "opmw"):
        return _weighted_runner(scheme, side)
    kind, h, family = scheme.kind, scheme.h, scheme.family

    def prepare():
        draws = H.draws(h, scheme.seed)
        block = {("opm1", "data"): H.PAD_A, ("opm2", "data"): H.PAD_A, ("opm2", "query"): H.PAD_B}.get((kind, side))
        stairs = staircase(h, scheme["m"], scheme.seed, family, block) if block and not scheme["explicit"] else None
        return draws, block, stairs

    def aux(draw: tuple, name: str) -> float:
        return H.gaussian(H.hash_values(np.array([H.py_fp(name)]), draw, family))[0] / H.UNIT

    def code(draw, sizes, flat, starts, ids, stairs, block, t):
        if kind in ("minhash", "opm1", "opm2"):
            raw = np.minimum.reduceat(H.hash_values(flat, draw, family), starts)
            if block is None:
                return raw, None
            need = np.maximum(scheme["m"] - sizes, 0)
            if stairs is None:
                low = np.minimum.accumulate(pad_hashes(scheme["m"], draw, family, block))
                pads = np.where(need > 0, np.concatenate([[np.iinfo(np.int64).max], low])[need], np.iinfo(np.int64).max)
            else:
                at, low = stairs[t]
                place = np.searchsorted(at, need, side="right") - 1
                pads = np.where(place >= 0, low[np.maximum(place, 0)] if len(low) else np.iinfo(np.int64).max, np.iinfo(np.int64).max)
            return np.minimum(raw, pads), pads < raw
        if kind in ("sampling", "bits"):
            universe = scheme["universe"]
            chosen = universe[draw[0] % len(universe)]
            hit = np.maximum.reduceat((flat == chosen).astype(np.int64), starts).astype(bool)
            if kind == "bits":
                return hit.astype(np.int64), None
            low = 1 if scheme["miss_range"] == "one_to_n" else 0
            own = np.array([H.py_fp(f"{side}:{i}") for i in ids.tolist()], np.int64)
            return np.where(hit, 0, low + H.hash_values(own, draw, family) % scheme["n"]), None
        sums = np.add.reduceat(H.gaussian(H.hash_values(flat, draw, family)), starts)
        if kind == "srp":
            return (sums >= 0).astype(np.int64), None
        real = sums / H.UNIT
        if kind == "srp2":
            cut = scheme["width"] * np.sqrt(sizes)
            return (real >= -cut).astype(np.int64) + (real >= 0) + (real >= cut), None
        if kind == "l2lsh":
            return np.floor((real + draw[5] * scheme["r"]) / scheme["r"]).astype(np.int64), None
        if kind == "normsign":
            v = scheme["v"]
            rest = np.sqrt(np.maximum(0.0, 1 - sizes / (v * v)))
            return (real / v + rest * aux(draw, H.AUX + ("0" if side == "data" else "1")) >= 0).astype(np.int64), None
        scale = scheme["u"] / scheme["v"]
        m = scheme["m"]
        powers, x = [], sizes * (scale * scale)
        for _ in range(m):
            powers.append(x)
            x = x * x
        flip = kind == "signalsh"
        extra = [0.5 - p if flip else p for p in powers]
        still = [np.zeros(len(sizes)) if flip else np.full(len(sizes), 0.5)] * m
        total = real * scale
        for j, value in enumerate([*extra, *still] if side == "data" else [*still, *extra]):
            total = total + value * aux(draw, f"{H.AUX}{j}")
        if flip:
            return (total >= 0).astype(np.int64), None
        return np.floor((total + draw[5] * scheme["r"]) / scheme["r"]).astype(np.int64), None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        draws, block, stairs = prepare()
        for batch in batches:
            step = max(1, CHUNK // max(1, h))
            for part in (batch.slice(i, step) for i in range(0, batch.num_rows, step)):
                ids, sizes, flat, starts = _sets_of(part)
                if not len(ids):
                    continue
                if kind == "oph":
                    codes, pads = _bins(scheme, side, sizes, flat, starts)
                else:
                    both = [code(d, sizes, flat, starts, ids, stairs, block, t) for t, d in enumerate(draws)]
                    codes = np.stack([c for c, _ in both], 1)
                    pads = np.stack([p for _, p in both], 1) if both[0][1] is not None else None
                offsets = pa.array(np.arange(0, len(ids) * h + 1, h, dtype=np.int32))
                sig = pa.ListArray.from_arrays(offsets, pa.array(codes.ravel()))
                flags = pa.nulls(len(ids), pa.list_(pa.bool_())) if pads is None else pa.ListArray.from_arrays(offsets, pa.array(pads.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(sizes.astype(np.int32)), sig, flags], names=["id", "f", "sig", "pad"])

    return run


def _bins(scheme: Scheme, side: str, sizes: np.ndarray, flat: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, None]:
    """One hash dealt into bins; an empty bin takes the next full bin's value, marked by its distance."""
    h = scheme.h
    draw = H.draws(1, scheme.seed)[0]
    values = H.hash_values(flat, draw, scheme.family)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    low = np.full((len(sizes), h), np.iinfo(np.int64).max)
    np.minimum.at(low, (owner, values % h), values // h)
    if scheme["m"] and side == "data":
        pads = pad_hashes(scheme["m"], draw, scheme.family, H.PAD_A)
        for i, n in enumerate(np.maximum(scheme["m"] - sizes, 0)):
            np.minimum.at(low[i], pads[:n] % h, pads[:n] // h)
    full = low < np.iinfo(np.int64).max
    place = np.where(full, np.arange(h), 2 * h)
    wide = np.concatenate([place, place + h], 1)
    nxt = np.minimum.accumulate(wide[:, ::-1], axis=1)[:, ::-1][:, :h]
    shift = nxt - np.arange(h)
    return np.take_along_axis(low, nxt % h, 1) + shift * (1 << 32), None


def signatures(sets: DataFrame, scheme: Scheme, side: str = "data") -> DataFrame:
    """``id, f, sig, pad``: ``pad`` marks codes that came from padding (null where a
    scheme does not pad).  Empty sets have no codes and are left out."""
    return sets.select("id", "elems").mapInArrow(runner(scheme, side), SIGNATURE)


def long_codes(sig: DataFrame, scheme: Scheme | None = None) -> DataFrame:
    """``id, t, code`` and, for padded schemes, ``from_pad``."""
    if scheme is not None and scheme.kind in ("opm1", "opm2") and "m" in scheme.params:
        return sig.select("id", F.posexplode(F.arrays_zip("sig", F.coalesce("pad", F.transform("sig", lambda c: F.lit(False))).alias("pad"))).alias("t", "x")).select("id", "t", F.col("x.sig").alias("code"), F.col("x.pad").alias("from_pad"))
    return sig.select("id", F.posexplode("sig").alias("t", "code"))


def repad(raw: DataFrame, scheme: Scheme, side: str = "data") -> DataFrame:
    """Padded signatures for any M out of stored raw signatures and sizes: no token is hashed again."""
    block = H.PAD_A if side == "data" else H.PAD_B
    if scheme.kind == "opm1" and side == "query":
        return raw

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stairs = staircase(scheme.h, scheme["m"], scheme.seed, scheme.family, block)
        most = np.iinfo(np.int64).max
        for batch in batches:
            sizes = batch.column(1).to_numpy()
            codes = batch.column(2).flatten().to_numpy().reshape(len(sizes), scheme.h)
            need = np.maximum(scheme["m"] - sizes, 0)
            pads = np.full(codes.shape, most)
            for t, (at, low) in enumerate(stairs):
                place = np.searchsorted(at, need, side="right") - 1
                if len(low):
                    pads[:, t] = np.where(place >= 0, low[np.maximum(place, 0)], most)
            offsets = pa.array(np.arange(0, codes.size + 1, scheme.h, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.ListArray.from_arrays(offsets, pa.array(np.minimum(codes, pads).ravel())), pa.ListArray.from_arrays(offsets, pa.array((pads < codes).ravel()))], names=["id", "f", "sig", "pad"])

    return raw.select("id", "f", "sig", "pad").mapInArrow(run, SIGNATURE)


# weighted sampling


def cws(h: int, seed: int) -> Scheme:
    return Scheme("cws", h, seed)


def opmw(h: int, seed: int, m: int) -> Scheme:
    """Padding as one coordinate of weight M - f on each side."""
    return Scheme("opmw", h, seed, "poly", {"m": m})


def weighted_opm(h: int, seed: int, m: float) -> Scheme:
    """The same for weighted overlap: M bounds the sum of weights."""
    return Scheme("opmw", h, seed, "poly", {"m": m})


def _uniform(elements: np.ndarray, draw: tuple, salt: int) -> np.ndarray:
    x = H.hash_values((elements * 5 + salt) % H.P, draw, "poly")
    return (x + 0.5) / H.P


def _weighted_runner(scheme: Scheme, side: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Batches of ``id, elems`` without weights have ones."""
    pad = {"data": H.py_fp("weight:A"), "query": H.py_fp("weight:B")}[side]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        draws = H.draws(scheme.h, scheme.seed)
        for batch in batches:
            ids, sizes = batch.column(0).to_numpy(), np.diff(batch.column(1).offsets.to_numpy())
            elems = batch.column(1).flatten().to_numpy(zero_copy_only=False)
            weights = batch.column(2).flatten().to_numpy(zero_copy_only=False).astype(float) if batch.num_columns > 2 else np.ones(len(elems))
            owner = np.repeat(np.arange(len(ids)), sizes)
            elems, weights, owner = elems[weights > 0], weights[weights > 0], owner[weights > 0]
            totals = np.bincount(owner, weights, minlength=len(ids))
            if scheme.kind == "opmw":
                rest = scheme["m"] - totals
                more = np.flatnonzero(rest > 0)
                elems, weights, owner = np.append(elems, np.full(len(more), pad)), np.append(weights, rest[more]), np.append(owner, more)
                order = np.argsort(owner, kind="stable")
                elems, weights, owner = elems[order], weights[order], owner[order]
            some = np.unique(owner)
            starts = np.searchsorted(owner, some)
            codes = np.zeros((len(some), scheme.h), np.int64)
            for t, draw in enumerate(draws if len(some) else ()):
                r = -np.log(_uniform(elems, draw, 0) * _uniform(elems, draw, 1))
                c = -np.log(_uniform(elems, draw, 2) * _uniform(elems, draw, 3))
                b = _uniform(elems, draw, 4)
                level = np.floor(np.log(weights) / r + b)
                y = np.exp(r * (level - b))
                score = c / (y * np.exp(r))
                least = np.flatnonzero(score == np.repeat(np.minimum.reduceat(score, starts), np.diff(starts, append=len(owner))))
                k = least[np.searchsorted(owner[least], some)]
                codes[:, t] = elems[k] * 8191 + level[k].astype(np.int64)
            offsets = pa.array(np.arange(0, codes.size + 1, scheme.h, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(totals[some]), pa.ListArray.from_arrays(offsets, pa.array(codes.ravel()))], names=["id", "total", "sig"])

    return run


def weighted_signatures(weighted: DataFrame, scheme: Scheme, side: str = "data") -> DataFrame:
    """``id, total, sig`` of ``(id, elems, weights)`` by consistent weighted sampling:
    codes agree with probability of the weighted resemblance.  Cost does not
    depend on M.  Weights that are not positive are left out."""
    return weighted.select("id", "elems", "weights").mapInArrow(_weighted_runner(scheme, side), "id bigint, total double, sig array<bigint>")


def as_weighted(sets: DataFrame) -> DataFrame:
    return sets.select("id", "elems", F.transform("elems", lambda e: F.lit(1.0)).alias("weights"))
