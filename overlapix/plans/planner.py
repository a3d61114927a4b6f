"""Decisions that are made while a plan is built, on checked sizes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a side that may be broadcast: some 100 bytes each.
BROADCAST_ROWS = 1_000_000


def broadcast_if_small(df: DataFrame, rows: int = BROADCAST_ROWS, required: bool = False) -> DataFrame:
    """``df`` with a broadcast hint if a count shows it to be small; else as it is,
    or an error where only a broadcast makes sense."""
    n = df.limit(rows + 1).count()
    if n <= rows:
        return F.broadcast(df)
    if required:
        raise ValueError(f"more than {rows} rows on the side that is to be broadcast")
    return df


def size_filter(f: str, fq: str, t: float):
    """Containment of at least ``t`` needs that many elements: a filter that the scan can take."""
    return F.col(f) >= F.ceil(F.lit(t) * F.col(fq) - 1e-9)


def live_fraction(sets: DataFrame, m: int, k: int) -> float:
    """Expected share of index rows that padding leaves probe-able."""
    return float(sets.agg(F.avg(F.pow(F.col("f") / F.greatest(F.lit(m), F.col("f")), F.lit(k)))).first()[0] or 0.0)


def size_bands(sets: DataFrame, base: float = 2.0) -> DataFrame:
    """Adds ``band``, so that sets of like size share a padding bound."""
    return sets.withColumn("band", F.floor(F.log(F.greatest("f", F.lit(1))) / F.log(F.lit(base)) + 1e-9).cast("int"))


def salts(buckets: DataFrame, keys: list[str], most: int) -> DataFrame:
    """``keys, n_salts``: into how many parts each bucket over ``most`` rows is dealt."""
    return buckets.groupBy(*keys).agg(F.count("*").alias("n")).where(F.col("n") > most).select(*keys, F.ceil(F.col("n") / most).cast("int").alias("n_salts"))


def salted_join(buckets: DataFrame, probes: DataFrame, keys: list[str], most: int = 100_000) -> DataFrame:
    """Inner join on ``keys`` where buckets of more than ``most`` rows are dealt into
    parts and their probes copied to each part; nothing is left out."""
    hot = F.broadcast(salts(buckets, keys, most))
    left = buckets.join(hot, keys, "left").withColumn("salt", F.pmod(F.xxhash64(*[c for c in buckets.columns if c not in keys]), F.coalesce("n_salts", F.lit(1))).cast("int")).drop("n_salts")
    right = probes.join(hot, keys, "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("n_salts", F.lit(1)) - 1))).drop("n_salts")
    return left.join(right, [*keys, "salt"]).drop("salt")
