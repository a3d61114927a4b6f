"""Building sets and their statistics.

A set is a row ``(id, elems, f)``: distinct sorted 31-bit fingerprints and their
number.  Text sets are made row by row, without a shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapix.functions.hashing import fp

#: Fixed value: what separates words.
SEPARATORS = r"[^\p{L}\p{N}]+"


def tokens(text: Column, lower: bool = True) -> Column:
    """Words in order, repeats kept; none for null."""
    text = F.coalesce(text, F.lit(""))
    return F.filter(F.split(F.lower(text) if lower else text, SEPARATORS), lambda w: w != "")


def _row(df: DataFrame, key: str, words: Column) -> DataFrame:
    elems = F.array_sort(F.transform(F.array_distinct(words), fp))
    made = df.select(F.col(key).cast("bigint").alias("id"), F.array_distinct(elems).alias("elems"))
    return made.withColumn("f", F.size("elems"))


def word_sets(df: DataFrame, key: str, text: str, lower: bool = True) -> DataFrame:
    return _row(df, key, tokens(F.col(text), lower))


def shingles(words: Column, k: int) -> Column:
    """Runs of ``k`` consecutive words joined by a space; none in a shorter text.

    ``k`` shifted copies are zipped, so ``words`` is evaluated per copy and not per shingle.
    """
    n = F.greatest(F.size(words) - k + 1, F.lit(0))
    shifted = F.arrays_zip(*[F.slice(words, i + 1, n) for i in range(k)])
    return F.transform(shifted, lambda z: F.concat_ws(" ", *[z[str(i)] for i in range(k)]))


def shingle_sets(df: DataFrame, key: str, text: str, k: int, unit: str = "word") -> DataFrame:
    """Sets of word or character shingles; texts too short for one give no row."""
    words = tokens(F.col(text)) if unit == "word" else F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), "")
    kept = df.select(F.col(key).alias("id"), words.alias("w"))
    joined = shingles(F.col("w"), k) if unit == "word" else F.transform(shingles(F.col("w"), k), lambda s: F.regexp_replace(s, " ", ""))
    return _row(kept.where(F.size("w") >= k), "id", joined)


def html_sets(df: DataFrame, key: str, html: str) -> DataFrame:
    return _row(df, key, tokens(F.regexp_replace(F.col(html), "<[^>]*>", " ")))


def incidence_sets(inc: DataFrame, key: str, token: str) -> DataFrame:
    """Sets from (id, token) rows; one shuffle, with partial collection before it."""
    made = inc.where(F.col(token).isNotNull()).groupBy(F.col(key).cast("bigint").alias("id")).agg(F.collect_set(fp(F.col(token))).alias("elems"))
    return made.select("id", F.array_sort("elems").alias("elems"), F.size("elems").alias("f"))


def binarize(df: DataFrame, key: str, vector: str, threshold: float = 0.0) -> DataFrame:
    """The coordinates, from 0, whose value is above the threshold."""
    at = F.filter(F.transform(F.col(vector), lambda v, i: F.when(v > threshold, i.cast("string"))), lambda s: s.isNotNull())
    return _row(df, key, at)


def weighted_sets(df: DataFrame, key: str, token: str, weight: str) -> DataFrame:
    """``(id, e, w)``: summed whole weights."""
    return df.groupBy(F.col(key).cast("bigint").alias("id"), fp(F.col(token)).alias("e")).agg(F.sum(weight).cast("bigint").alias("w"))


def incidence(sets: DataFrame) -> DataFrame:
    """``(id, e)``, the long form."""
    return sets.select("id", F.explode("elems").alias("e"))


def is_query(key: Column, parts: int = 10) -> Column:
    return fp(F.concat(F.lit("q:"), key.cast("string"))) % parts == 0


def split_partitions(sets: DataFrame, parts: int = 10) -> tuple[DataFrame, DataFrame]:
    """(train, queries) by a hash of the id; a filter on each side, no shuffle."""
    return sets.where(~is_query(F.col("id"), parts)), sets.where(is_query(F.col("id"), parts))


def set_profile(sets: DataFrame) -> DataFrame:
    """Array-free digest of each set: ``id, f, fp_sum, fp_min``."""
    return sets.select("id", F.col("f").cast("bigint").alias("f"), F.aggregate("elems", F.lit(0).cast("bigint"), lambda a, e: a + e).alias("fp_sum"), F.array_min("elems").alias("fp_min"))


def set_stats(sets: DataFrame, name: str) -> DataFrame:
    """One row of size statistics; dimensions are counted from the long form."""
    base = sets.agg(
        F.count(F.when(is_query(F.col("id")), 1)).alias("n_query"), F.count(F.when(~is_query(F.col("id")), 1)).alias("n_train"),
        F.round(F.avg("f"), 4).alias("mean_f"), F.round(F.stddev_pop("f"), 4).alias("std_f"), F.max("f").cast("bigint").alias("max_f"),
    )
    dims = incidence(sets).agg(F.countDistinct("e").alias("n_dim"))
    return base.crossJoin(dims).select(F.lit(name).alias("collection"), "n_query", "n_train", "n_dim", "mean_f", "std_f", "max_f")


def size_profile(sets: DataFrame, width: int = 50) -> DataFrame:
    """Histogram of sizes with the coefficient of variation and max over mean."""
    total = sets.agg(F.round(F.stddev_pop("f") / F.avg("f"), 6).alias("cv"), F.round(F.max("f") / F.avg("f"), 6).alias("max_over_mean"))
    return sets.groupBy(F.floor(F.col("f") / width).alias("band")).agg(F.count("*").alias("n")).crossJoin(F.broadcast(total)).select("band", "n", "cv", "max_over_mean")


def element_frequency(sets: DataFrame) -> DataFrame:
    """``e, df, rank``: ranks in descending frequency, ties sharing the least."""
    counts = incidence(sets).groupBy("e").agg(F.count("*").alias("df"))
    # ranks come from the frequencies' own histogram, which is short, and not from a window over all elements
    levels = counts.groupBy("df").agg(F.count("*").alias("n"))
    above = levels.select("df", (F.coalesce(F.sum("n").over(Window.orderBy(F.desc("df")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) + 1).alias("rank"))
    return counts.join(F.broadcast(above), "df").select("e", "df", "rank")


def dense_ids(df: DataFrame, *order) -> DataFrame:
    """Adds ``eid`` from 1 in ``order``, over range partitions whose sizes are summed; no window over all rows."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    numbered = ranged.withColumn("__p", F.spark_partition_id()).withColumn("__i", F.monotonically_increasing_id())
    sizes = numbered.groupBy("__p").agg(F.count("*").alias("n"), F.min("__i").alias("first"))
    before = sizes.select("__p", "first", F.coalesce(F.sum("n").over(Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return numbered.join(F.broadcast(before), "__p").withColumn("eid", F.col("base") + F.col("__i") - F.col("first") + 1).drop("__p", "__i", "first", "base")


def build_dictionary(sets: DataFrame) -> DataFrame:
    """``eid, e, df``: elements numbered by descending frequency, then by value."""
    counts = incidence(sets).groupBy("e").agg(F.count("*").alias("df"))
    return dense_ids(counts, F.desc("df"), F.asc("e")).select("eid", "e", "df")


def padding_bound(sets: DataFrame, policy: str = "data", queries: DataFrame | None = None, quantile: float = 0.999, fixed: int | None = None) -> int:
    """M: the size that sets are padded to.  One small aggregate and one number to the driver."""
    if policy == "fixed":
        return int(fixed or 0)
    pool = sets.select("f")
    if policy == "data_and_query" and queries is not None:
        pool = pool.unionByName(queries.select("f"))
    if policy == "quantile":
        return int(pool.agg(F.percentile("f", F.lit(quantile))).first()[0] or 0)
    return int(pool.agg(F.max("f")).first()[0] or 0)


def split_outliers(sets: DataFrame, m: int) -> tuple[DataFrame, DataFrame]:
    return sets.where(F.col("f") <= m), sets.where(F.col("f") > m)
