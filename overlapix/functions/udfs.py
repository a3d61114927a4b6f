"""Vectorised scalar, aggregate and table functions, and names for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from overlapix.functions import hashing as H
from overlapix.functions import theory


def minhash_codes(h: int, seed: int, family: str = "poly"):
    """Column function: array of fingerprints -> array of codes; null for an empty set."""

    @pandas_udf("array<bigint>")
    def codes(elems: pd.Series) -> pd.Series:
        draws = H.draws(h, seed)
        return elems.map(lambda e: None if e is None or not len(e) else [int(H.hash_values(np.asarray(e, np.int64), d, family).min()) for d in draws])

    return codes


def f_r_udf():
    @pandas_udf("double")
    def law(d: pd.Series, r: pd.Series) -> pd.Series:
        return pd.Series([theory.f_r(x, y) for x, y in zip(d, r, strict=True)], dtype="float64")

    return law


def minhash_agg(h: int, seed: int):
    """Grouped aggregate over element rows: the signature of a group.  A group sits
    in memory whole, so ``minhash_columns`` is the form for groups of any size."""

    @pandas_udf("array<bigint>")
    def agg(e: pd.Series) -> list:
        x = e.to_numpy(np.int64)
        return [int(H.hash_values(x, d, "poly").min()) for d in H.draws(h, seed)]

    return agg


def minhash_columns(column: str, h: int, seed: int) -> list:
    """``h`` native minima of affine hashes, with partial aggregation."""
    return [F.min((F.col(column) * a + b) % H.P).alias(f"c{t}") for t, (a, b, *_) in enumerate(H.draws(h, seed))]


@udtf(returnType="j: int, key: string")
class Bands:
    """(signature, K, L) -> one row a table: its number and key."""

    def eval(self, sig: list, k: int, l: int) -> Iterator[tuple]:  # noqa: E741
        for j in range(l):
            yield j, "-".join(map(str, sig[j * k : (j + 1) * k]))


def register(spark: SparkSession) -> None:
    """SQL names: ``set_overlap``, ``set_containment``, ``opm1_sim`` as SQL functions, ``bands`` as a table function."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_overlap(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BIGINT RETURN size(array_intersect(a, b))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_containment(q ARRAY<BIGINT>, x ARRAY<BIGINT>) RETURNS DOUBLE RETURN CASE WHEN size(q) > 0 THEN size(array_intersect(q, x)) / size(q) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION opm1_sim(a BIGINT, fq BIGINT, m BIGINT) RETURNS DOUBLE RETURN a / (m + fq - a)")
    spark.udtf.register("bands", Bands)
