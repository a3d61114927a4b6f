"""Ranking by matching codes, and its precision and recall."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapix.operators.exact import tie_order
from overlapix.plans.planner import broadcast_if_small

#: Queries that a task holds at a time; more come in further passes over the sets.
MAX_QUERIES = 5000


def _blocks(qsig: DataFrame) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Ids and codes of the queries, ``MAX_QUERIES`` at a time."""
    ids: list[int] = []
    codes: list = []
    for r in qsig.select("id", "sig").toLocalIterator():
        ids.append(r.id)
        codes.append(r.sig)
        if len(ids) == MAX_QUERIES:
            yield np.array(ids, np.int64), np.array(codes, np.int64)
            ids, codes = [], []
    if ids:
        yield np.array(ids, np.int64), np.array(codes, np.int64)


def _agreements(batches: Iterator[pa.RecordBatch], codes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Ids of sets and, for each set and query, which codes agree."""
    for batch in batches:
        ids = batch.column(0).to_numpy()
        if not len(ids):
            continue
        own = batch.column(1).flatten().to_numpy().reshape(len(ids), -1)
        step = max(1, (1 << 22) // max(1, codes.size))
        for a in range(0, len(ids), step):
            yield ids[a : a + step], own[a : a + step, None, :] == codes[None, :, :]


def match_counts(xsig: DataFrame, qsig: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """``q_id, x_id, k, matches`` for every query and set: agreements among the first k codes.

    Queries travel with the tasks, ``MAX_QUERIES`` a pass; sets stream past them in
    blocks, so one pass serves every k.
    """
    schema = "q_id bigint, x_id bigint, k int, matches bigint"

    def one(qids: np.ndarray, codes: np.ndarray) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for ids, same in _agreements(batches, codes):
                x, q = np.repeat(ids, len(qids)), np.tile(qids, len(ids))
                for k in ks:
                    yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(x), pa.array(np.full(len(x), k, np.int32)), pa.array(same[:, :, :k].sum(2).ravel().astype(np.int64))], names=["q_id", "x_id", "k", "matches"])

        return xsig.select("id", "sig").mapInArrow(run, schema)

    return _united([one(*b) for b in _blocks(qsig)], xsig, schema)


def _united(parts: list[DataFrame], like: DataFrame, schema: str) -> DataFrame:
    out = parts[0] if parts else like.sparkSession.createDataFrame([], schema)
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def tie_groups(xsig: DataFrame, qsig: DataFrame, gold: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """``q_id, k, matches, n, g``: how many sets, and how many of the gold, have so many matches.

    Sets are counted inside the tasks; a query has at most k + 1 rows, however many sets there are.
    """
    schema = "q_id bigint, k int, matches bigint, n bigint"

    def one(qids: np.ndarray, codes: np.ndarray) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = {k: np.zeros((len(qids), k + 1), np.int64) for k in ks}
            for _, same in _agreements(batches, codes):
                for k in ks:
                    place = same[:, :, :k].sum(2) + np.arange(len(qids)) * (k + 1)
                    total[k] += np.bincount(place.ravel(), minlength=total[k].size).reshape(total[k].shape)
            for k in ks:
                q, m = np.nonzero(total[k])
                yield pa.RecordBatch.from_arrays([pa.array(qids[q]), pa.array(np.full(len(q), k, np.int32)), pa.array(m.astype(np.int64)), pa.array(total[k][q, m])], names=["q_id", "k", "matches", "n"])

        return xsig.select("id", "sig").mapInArrow(run, schema)

    sizes = _united([one(*b) for b in _blocks(qsig)], xsig, schema).groupBy("q_id", "k", "matches").agg(F.sum("n").alias("n"))
    pairs = gold.select("q_id", "x_id").join(xsig.select(F.col("id").alias("x_id"), F.col("sig").alias("xs")), "x_id").join(qsig.select(F.col("id").alias("q_id"), F.col("sig").alias("qs")), "q_id")
    same = F.zip_with("xs", "qs", lambda a, b: (a == b).cast("int"))
    found = None
    for k in ks:
        met = pairs.select("q_id", F.lit(k).alias("k"), F.aggregate(F.slice(same, 1, k), F.lit(0).cast("bigint"), lambda a, b: a + b).alias("matches"))
        found = met if found is None else found.unionByName(met)
    hits = found.groupBy("q_id", "k", "matches").agg(F.count("*").alias("g"))
    return sizes.join(hits, ["q_id", "k", "matches"], "left").select("q_id", "k", "matches", "n", F.coalesce("g", F.lit(0).cast("bigint")).alias("g"))


def tie_curve(groups: DataFrame, levels: int = 10) -> DataFrame:
    """``k, level, precision_``: the mean over queries with gold of the best precision at
    each recall level or beyond, at the ends of tie groups."""
    run = Window.partitionBy("q_id", "k").orderBy(F.desc("matches")).rowsBetween(Window.unboundedPreceding, 0)
    walk = groups.select("q_id", "k", F.sum("n").over(run).alias("p"), F.sum("g").over(run).alias("seen"), F.sum("g").over(Window.partitionBy("q_id", "k")).alias("total")).where("total > 0")
    at = walk.select("q_id", "k", (F.col("seen") / F.col("p")).alias("precision_"), (F.col("seen") / F.col("total")).alias("recall"), F.explode(F.sequence(F.lit(1), F.lit(levels))).alias("level"))
    best = at.where(F.col("recall") >= F.col("level") / levels - 1e-12).groupBy("q_id", "k", "level").agg(F.max("precision_").alias("precision_"))
    return best.groupBy("k", "level").agg(F.round(F.avg("precision_"), 6).alias("precision_"))


def sparse_match_counts(xsig: DataFrame, qsig: DataFrame, k: int) -> DataFrame:
    """The same counts, for pairs that match at all, as a join on (t, code)."""
    x = xsig.select(F.col("id").alias("x_id"), F.posexplode(F.slice("sig", 1, k)).alias("t", "code"))
    q = qsig.select(F.col("id").alias("q_id"), F.posexplode(F.slice("sig", 1, k)).alias("t", "code"))
    return x.join(q, ["t", "code"]).groupBy("q_id", "x_id").agg(F.count("*").alias("matches"))


def rank_by_matches(counts: DataFrame) -> DataFrame:
    """Adds ``p``, the place in each query's list; ties by the id's fingerprint."""
    w = Window.partitionBy("k", "q_id").orderBy(F.desc("matches"), *tie_order())
    return counts.withColumn("p", F.row_number().over(w).cast("bigint"))


def pr_points(ranked: DataFrame, gold: DataFrame) -> DataFrame:
    """``q_id, k, p, is_gold, relevant_seen, precision_, recall``; queries without gold are left out."""
    sizes = gold.groupBy("q_id").agg(F.count("*").alias("g"))
    marked = ranked.join(broadcast_if_small(sizes), "q_id").join(broadcast_if_small(gold.select("q_id", "x_id", F.lit(1).alias("hit"))), ["q_id", "x_id"], "left")
    walk = Window.partitionBy("k", "q_id").orderBy("p").rowsBetween(Window.unboundedPreceding, 0)
    seen = marked.withColumn("is_gold", F.coalesce("hit", F.lit(0))).withColumn("relevant_seen", F.sum("is_gold").over(walk).cast("bigint"))
    return seen.select("q_id", "k", "p", "is_gold", "relevant_seen", F.round(F.col("relevant_seen") / F.col("p"), 6).alias("precision_"), F.round(F.col("relevant_seen") / F.col("g"), 6).alias("recall"), "g")


def mean_pr(points: DataFrame) -> DataFrame:
    return points.groupBy("k", "p").agg(F.round(F.avg(F.col("relevant_seen") / F.col("p")), 6).alias("precision_"), F.round(F.avg(F.col("relevant_seen") / F.col("g")), 6).alias("recall"))


def interpolated(points: DataFrame, levels: int = 10) -> DataFrame:
    """Mean over queries of the best precision at each recall level or beyond."""
    grid = F.explode(F.sequence(F.lit(1), F.lit(levels)))
    hits = points.where("is_gold = 1").select("q_id", "k", (F.col("relevant_seen") / F.col("p")).alias("precision_"), (F.col("relevant_seen") / F.col("g")).alias("recall"), grid.alias("level"))
    best = hits.where(F.col("recall") >= F.col("level") / levels - 1e-12).groupBy("q_id", "k", "level").agg(F.max("precision_").alias("precision_"))
    return best.groupBy("k", "level").agg(F.round(F.avg("precision_"), 6).alias("precision_"))


def average_precision(points: DataFrame) -> DataFrame:
    """``k, n_queries, ap``: the mean of each query's mean precision at its gold."""
    one = points.where("is_gold = 1").groupBy("k", "q_id").agg((F.sum(F.col("relevant_seen") / F.col("p")) / F.max("g")).alias("ap"))
    return one.groupBy("k").agg(F.count("*").alias("n_queries"), F.round(F.avg("ap"), 6).alias("ap"))


def precision_at(ranked: DataFrame, gold: DataFrame, t: int) -> DataFrame:
    hit = ranked.where(F.col("p") <= t).join(broadcast_if_small(gold.select("q_id", "x_id")), ["q_id", "x_id"])
    return hit.groupBy("k", "q_id").agg((F.count("*") / F.lit(t)).alias("precision_"))


def estimate_overlap(matches: Column, k: int, fq: Column, m: int, kind: str = "opm1") -> Column:
    """The overlap at which the padded law gives the seen share of matches."""
    r = matches / F.lit(k)
    return r * ((F.lit(m) + fq) if kind == "opm1" else F.lit(2 * m)) / (1 + r)
