"""Exact overlap, search and the non-hashing baselines."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapix.functions import measures
from overlapix.functions.hashing import fp
from overlapix.operators.sets import incidence
from overlapix.plans.planner import broadcast_if_small

MEASURES: dict[str, Callable[[Column, Column, Column], Column]] = {
    "overlap": lambda a, fq, fx: a.cast("double"),
    "containment": lambda a, fq, fx: measures.containment(a, fq),
    "resemblance": lambda a, fq, fx: measures.resemblance(a, fx, fq),
}


def overlaps(train: DataFrame, queries: DataFrame) -> DataFrame:
    """``q_id, x_id, a, fq, fx`` of every pair that shares an element.

    An equi-join of the long forms on the element, counted with partial sums; a
    query side of proven size is broadcast, so data elements are not shuffled.
    """
    q = queries.select(F.col("id").alias("q_id"), F.col("f").cast("bigint").alias("fq"), F.explode("elems").alias("e"))
    x = train.select(F.col("id").alias("x_id"), F.col("f").cast("bigint").alias("fx"), F.explode("elems").alias("e"))
    return x.join(broadcast_if_small(q), "e").groupBy("q_id", "x_id", "fq", "fx").agg(F.count("*").alias("a")).select("q_id", "x_id", "a", "fq", "fx")


def tie_order(key: str = "x_id") -> list[Column]:
    """Equal scores are ordered by the id's fingerprint, then by the id."""
    return [fp(F.col(key).cast("string")), F.col(key)]


def top_t(scored: DataFrame, t: int, score: str = "score", key: str = "x_id") -> DataFrame:
    """Best ``t`` per query with ``rank``; the rank filter becomes a group limit before the shuffle."""
    w = Window.partitionBy("q_id").orderBy(F.desc(score), *tie_order(key))
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= t)


def exact_topk(train: DataFrame, queries: DataFrame, t: int, measure: str = "containment") -> DataFrame:
    """``q_id, rank, x_id, a``; pairs without overlap are no answers."""
    scored = overlaps(train, queries).withColumn("score", MEASURES[measure](F.col("a"), F.col("fq"), F.col("fx")))
    return top_t(scored, t).select("q_id", F.col("rank").cast("bigint").alias("rank"), "x_id", "a")


def mips(train: DataFrame, queries: DataFrame) -> DataFrame:
    return exact_topk(train, queries, 1, "overlap").select("q_id", "x_id", "a")


def mcs(train: DataFrame, queries: DataFrame) -> DataFrame:
    return exact_topk(train, queries, 1, "containment").select("q_id", "x_id", "a")


def near_neighbors(train: DataFrame, queries: DataFrame, s0: int) -> DataFrame:
    return overlaps(train, queries).where(F.col("a") >= s0).select("q_id", "x_id", "a")


def is_cnn_answer(answers: DataFrame, best: DataFrame, s0: int, c: float) -> DataFrame:
    """Whether each query's answer is as good as the c-approximate problem asks."""
    joined = best.select("q_id", F.col("a").alias("best")).join(answers.select("q_id", F.col("a").alias("got")), "q_id", "left")
    return joined.select("q_id", "best", "got", ((F.col("best") < s0) | (F.coalesce("got", F.lit(0)) >= c * s0)).alias("ok"))


def linear_scan(train: DataFrame, queries: DataFrame, measure: str = "containment") -> DataFrame:
    """Every query against every set, in the order sets come: the yardstick of cost.
    The query set is given and bounded, and each of its rows meets a stream of sets."""
    q = queries.select(F.col("id").alias("q_id"), F.col("elems").alias("qe"), F.col("f").cast("bigint").alias("fq"))
    x = train.select(F.col("id").alias("x_id"), F.col("elems").alias("xe"), F.col("f").cast("bigint").alias("fx"))
    pairs = x.join(broadcast_if_small(q, required=True), F.lit(True))
    a = pairs.withColumn("a", measures.overlap(F.col("qe"), F.col("xe")).cast("bigint")).where("a > 0")
    return a.select("q_id", "x_id", "a", F.round(MEASURES[measure](F.col("a"), F.col("fq"), F.col("fx")), 6).alias("value"))


class InvertedIndex:
    """Postings (e, id, f) of a collection, with each element's frequency."""

    def __init__(self, train: DataFrame) -> None:
        self.postings = train.select(F.explode("elems").alias("e"), F.col("id").alias("x_id"), F.col("f").cast("bigint").alias("fx"))
        self.df = self.postings.groupBy("e").agg(F.count("*").alias("df"))

    def search(self, queries: DataFrame, t: int) -> DataFrame:
        """Count-merge of the postings of a query's elements."""
        q = queries.select(F.col("id").alias("q_id"), F.explode("elems").alias("e"))
        counted = self.postings.join(broadcast_if_small(q), "e").groupBy("q_id", "x_id").agg(F.count("*").alias("a"))
        return top_t(counted.withColumn("score", F.col("a")), t).select("q_id", F.col("rank").cast("bigint").alias("rank"), "x_id", "a")

    def _ordered(self, queries: DataFrame) -> DataFrame:
        """A query's elements from rarest to commonest; elements of no posting come first."""
        q = queries.select(F.col("id").alias("q_id"), F.col("f").cast("bigint").alias("fq"), F.explode("elems").alias("e"))
        with_df = q.join(self.df, "e", "left").select("q_id", "fq", "e", F.coalesce("df", F.lit(0)).alias("df"))
        return with_df.withColumn("place", F.row_number().over(Window.partitionBy("q_id").orderBy("df", "e")))

    def prefix(self, queries: DataFrame, t: float) -> DataFrame:
        """The rarest elements of which a set of containment ``t`` must hold one."""
        need = F.ceil(F.lit(t) * F.col("fq") - 1e-9)
        return self._ordered(queries).where(F.col("place") <= F.col("fq") - need + 1)

    def search_threshold(self, train: DataFrame, queries: DataFrame, t: float) -> DataFrame:
        """Sets of containment at least ``t``: probe prefixes, then verify."""
        probes = broadcast_if_small(self.prefix(queries, t).select("q_id", "e"))
        cands = self.postings.join(probes, "e").select("q_id", "x_id").distinct()
        q = broadcast_if_small(queries.select(F.col("id").alias("q_id"), F.col("elems").alias("qe"), F.col("f").cast("bigint").alias("fq")))
        sized = cands.join(train.select(F.col("id").alias("x_id"), F.col("elems").alias("xe")), "x_id").join(q, "q_id")
        found = sized.withColumn("a", measures.overlap(F.col("qe"), F.col("xe")).cast("bigint"))
        return found.where(F.col("a") >= F.ceil(F.lit(t) * F.col("fq") - 1e-9)).select("q_id", "x_id", "a")

    def postings_touched(self, queries: DataFrame, t: float | None = None) -> DataFrame:
        """``q_id, fq, touched``: entries read by count-merge, or by prefixes at ``t``."""
        probes = self._ordered(queries) if t is None else self.prefix(queries, t)
        return probes.groupBy("q_id", "fq").agg(F.sum("df").cast("bigint").alias("touched"))


def minimal_infrequent_pairs(sets: DataFrame, max_df: int) -> DataFrame:
    """Pairs of elements that are each in more than ``max_df`` sets but together in
    at most that many and at least one: ``e1, e2, n``.  Rare elements go before
    the self-join, which runs inside each set."""
    inc = incidence(sets)
    common = inc.groupBy("e").agg(F.count("*").alias("df")).where(F.col("df") > max_df).select("e")
    kept = inc.join(common, "e", "left_semi").groupBy("id").agg(F.array_sort(F.collect_list("e")).alias("s"))
    pairs = kept.select(F.explode("s").alias("e1"), "s").select("e1", F.explode(F.filter("s", lambda e: e > F.col("e1"))).alias("e2"))
    return pairs.groupBy("e1", "e2").agg(F.count("*").alias("n")).where(F.col("n") <= max_df)


def ranking_overlap(first: DataFrame, second: DataFrame) -> DataFrame:
    """``q_id, shared``: how many answers two top lists have in common."""
    met = first.select("q_id", "x_id").join(second.select("q_id", "x_id"), ["q_id", "x_id"]).groupBy("q_id").agg(F.count("*").alias("shared"))
    return first.select("q_id").distinct().join(met, "q_id", "left").select("q_id", F.coalesce("shared", F.lit(0)).alias("shared"))
