"""Registered queries: sets, statistics, exact measures and search, theory."""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapix.functions import measures as M
from overlapix.functions import theory as T
from overlapix.operators import exact, sets, tiles
from overlapix.operators import transforms as tr
from overlapix.plans import oracle as O
from overlapix.plans.registry import add, query
from overlapix.sources.tables import bought, collection, kept, load

# sets and statistics


def _profile(coll: str):
    return lambda spark, d: sets.set_profile(collection(spark, d, coll).where("f > 0"))


def _profile_sql(coll: str) -> str:
    return O.query(O.base(coll), "SELECT id, CAST(count(*) AS BIGINT) AS f, CAST(sum(e) AS BIGINT) AS fp_sum, min(e) AS fp_min FROM inc GROUP BY id")


for _name, _coll in {"set_words": "docs_w", "set_shingles": "docs_s3", "set_baskets": "cust_parts", "set_binarize": "emb_bin", "set_pages": "pages_w", "set_hours": "user_hours"}.items():
    add(_name, _profile(_coll), _profile_sql(_coll))


@query(f"SELECT id, e, CAST(sum(w) AS BIGINT) AS w FROM (SELECT id, {O.fp('CAST(part AS VARCHAR)')} AS e, w FROM ({O.BOUGHT})) GROUP BY id, e")
def set_weighted(spark: SparkSession, d: str) -> DataFrame:
    return sets.weighted_sets(bought(spark, d), "id", "token", "w")


@query(O.query(O.base("docs_w"), "SELECT CAST(row_number() OVER (ORDER BY count(*) DESC, e) AS BIGINT) AS eid, e, CAST(count(*) AS BIGINT) AS df FROM inc GROUP BY e"))
def element_dictionary(spark: SparkSession, d: str) -> DataFrame:
    return sets.build_dictionary(collection(spark, d, "docs_w"))


@query(O.query(O.base("docs_w"), f"SELECT id, {O.is_query()} AS is_query FROM sets"))
def split_train_query(spark: SparkSession, d: str) -> DataFrame:
    train, queries = sets.split_partitions(collection(spark, d, "docs_w").where("f > 0"))
    return train.select("id", F.lit(False).alias("is_query")).unionByName(queries.select("id", F.lit(True).alias("is_query")))


STATS = ("docs_w", "docs_s3", "pages_w", "conv_w", "turn_w", "cust_parts", "order_parts", "part_supps", "user_hours", "emb_bin", "bench_w")


def _stats_sql(coll: str) -> str:
    return f"SELECT '{coll}' AS collection, CAST(count(*) FILTER ({O.is_query()}) AS BIGINT) AS n_query, CAST(count(*) FILTER (NOT ({O.is_query()})) AS BIGINT) AS n_train, (SELECT CAST(count(DISTINCT e) AS BIGINT) FROM {coll}_inc) AS n_dim, round(avg(f), 4) AS mean_f, round(stddev_pop(f), 4) AS std_f, CAST(max(f) AS BIGINT) AS max_f FROM {coll}_sets"


@query(O.query([x for c in STATS for x in O.base(c, f"{c}_")], " UNION ALL ".join(map(_stats_sql, STATS))))
def table1_stats(spark: SparkSession, d: str) -> DataFrame:
    frames = [sets.set_stats(collection(spark, d, c).where("f > 0"), c) for c in STATS]
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


@query(O.query(O.base("docs_w"), "SELECT CAST(f // 50 AS BIGINT) AS band, CAST(count(*) AS BIGINT) AS n, (SELECT round(stddev_pop(f) / avg(f), 6) FROM sets) AS cv, (SELECT round(max(f) / avg(f), 6) FROM sets) AS max_over_mean FROM sets GROUP BY f // 50"))
def size_profile(spark: SparkSession, d: str) -> DataFrame:
    return sets.size_profile(collection(spark, d, "docs_w").where("f > 0"))


BOUND_POLICIES = ("data", "data_and_query", "quantile")


@query(O.query(O.split("docs_w"), "SELECT 'data' AS policy, CAST(max(f) AS BIGINT) AS m FROM xsets UNION ALL SELECT 'data_and_query', CAST(max(f) AS BIGINT) FROM sets UNION ALL SELECT 'quantile', CAST(floor(quantile_cont(f, 0.999)) AS BIGINT) FROM xsets"))
def padding_bound(spark: SparkSession, d: str) -> DataFrame:
    train, queries = sets.split_partitions(collection(spark, d, "docs_w"))
    rows = [(p, sets.padding_bound(train, p, queries)) for p in BOUND_POLICIES]
    return spark.createDataFrame(rows, "policy string, m bigint")


@query(O.query(O.base("docs_w"), "SELECT f > 1000 AS outlier, CAST(count(*) AS BIGINT) AS n, CAST(sum(f) AS BIGINT) AS elements FROM sets GROUP BY f > 1000"))
def outlier_split(spark: SparkSession, d: str) -> DataFrame:
    parts = sets.split_outliers(collection(spark, d, "docs_w").where("f > 0"), 1000)
    made = [p.select(F.lit(flag).alias("outlier"), "f") for p, flag in zip(parts, (False, True), strict=True)]
    return made[0].unionByName(made[1]).groupBy("outlier").agg(F.count("*").alias("n"), F.sum("f").alias("elements"))


@query(O.query(O.base("docs_w"), "SELECT e, CAST(df AS BIGINT) AS df, CAST(rank() OVER (ORDER BY df DESC) AS BIGINT) AS rank FROM (SELECT e, count(*) AS df FROM inc GROUP BY e)"))
def element_frequency(spark: SparkSession, d: str) -> DataFrame:
    return sets.element_frequency(collection(spark, d, "docs_w"))


# exact measures: benchmark passages against documents

BOUND = 2000


def passages(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return collection(spark, d, "docs_w"), collection(spark, d, "bench_w")


PASSAGE = [*O.pair("docs_w", "bench_w"), O.OV]


def _measure(name: str, column, sql: str) -> None:
    add(
        name,
        lambda spark, d: exact.overlaps(*passages(spark, d)).select("q_id", "x_id", "a", "fq", "fx", F.round(column().cast("double"), 6).alias("value")),
        O.query(PASSAGE, f"SELECT q_id, x_id, CAST(a AS BIGINT) AS a, CAST(fq AS BIGINT) AS fq, CAST(fx AS BIGINT) AS fx, round(CAST({sql} AS DOUBLE), 6) AS value FROM ov"),
    )


_measure("exact_overlap", lambda: F.col("a"), "a")
_measure("exact_resemblance", lambda: M.resemblance(F.col("a"), F.col("fx"), F.col("fq")), "a / (fx + fq - a)")
_measure("exact_containment", lambda: M.containment(F.col("a"), F.col("fq")), "a / fq")
_measure("exact_cosine", lambda: M.cosine_sets(F.col("a"), F.col("fx"), F.col("fq")), "a / sqrt(fx * fq)")
_measure("exact_hamming", lambda: M.hamming(F.col("a"), F.col("fx"), F.col("fq")), "fx + fq - 2 * a")
_measure("sim_opm1", lambda: M.sim_opm1(F.col("a"), F.col("fq"), BOUND), f"a / ({BOUND} + fq - a)")
_measure("sim_opm2", lambda: M.sim_opm2(F.col("a"), BOUND), f"a / (2 * {BOUND} - a)")
_measure("distance_resemblance", lambda: M.as_distance(M.resemblance(F.col("a"), F.col("fx"), F.col("fq"))), "1 - a / (fx + fq - a)")

CUST_W = f"cw AS MATERIALIZED (SELECT id, e, CAST(sum(w) AS BIGINT) AS w FROM (SELECT id, {O.fp('CAST(part AS VARCHAR)')} AS e, w FROM ({O.BOUGHT})) GROUP BY id, e)"
WEIGHT_PAIRS = [CUST_W, "tot AS (SELECT id, sum(w) AS s FROM cw GROUP BY id)", f"wp AS MATERIALIZED (SELECT q.id AS q_id, x.id AS x_id, sum(least(q.w, x.w)) AS low FROM (SELECT * FROM cw WHERE {O.is_query()}) q JOIN (SELECT * FROM cw WHERE NOT ({O.is_query()})) x USING (e) GROUP BY q.id, x.id)"]


def weighted(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(train, queries) of customers' part quantities as ``id, elems, weights``."""
    rows = sets.weighted_sets(bought(spark, d), "id", "token", "w")
    made = rows.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("e", "w"))).alias("p")).select("id", F.col("p.e").alias("elems"), F.col("p.w").cast("array<double>").alias("weights"))
    return sets.split_partitions(made)


@query(O.query(WEIGHT_PAIRS, "SELECT q_id, x_id, round(CAST(low AS DOUBLE) / (a.s + b.s - low), 6) AS value FROM wp JOIN tot a ON a.id = q_id JOIN tot b ON b.id = x_id"))
def exact_weighted_jaccard(spark: SparkSession, d: str) -> DataFrame:
    return tr.weighted_pairs(*weighted(spark, d)).select("q_id", "x_id", F.round(F.col("low") / F.col("high"), 6).alias("value"))


@query(O.query(WEIGHT_PAIRS, "SELECT q_id, x_id, CAST(low AS BIGINT) AS value FROM wp"))
def exact_weighted_overlap(spark: SparkSession, d: str) -> DataFrame:
    return tr.weighted_pairs(*weighted(spark, d)).select("q_id", "x_id", F.col("low").cast("bigint").alias("value"))


@query(O.query(WEIGHT_PAIRS, f"SELECT q_id, CAST(rn AS BIGINT) AS rank, x_id, CAST(low AS BIGINT) AS value FROM (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY low DESC, {O.TIE}) AS rn FROM wp) WHERE rn <= 10"))
def weighted_topk(spark: SparkSession, d: str) -> DataFrame:
    return exact.top_t(tr.weighted_pairs(*weighted(spark, d)), 10, "low").select("q_id", F.col("rank").cast("bigint").alias("rank"), "x_id", F.col("low").cast("bigint").alias("value"))


@query(f"""WITH v AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)
SELECT q.id AS q_id, x.id AS x_id, round(list_inner_product(q.v, x.v), 5) AS dot, round(list_inner_product(q.v, x.v) / (sqrt(list_inner_product(q.v, q.v)) * sqrt(list_inner_product(x.v, x.v))), 5) AS cos, round(list_distance(q.v, x.v), 5) AS l2
FROM (SELECT * FROM v WHERE {O.is_query()}) q CROSS JOIN (SELECT * FROM v WHERE NOT ({O.is_query()})) x""")
def exact_dense_measures(spark: SparkSession, d: str) -> DataFrame:
    rows = load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    x = rows.where(~sets.is_query(F.col("id"))).select(F.col("id").alias("x_id"), F.col("v").alias("xv"))
    q = rows.where(sets.is_query(F.col("id"))).select(F.col("id").alias("q_id"), F.col("v").alias("qv"))
    both = x.join(exact.broadcast_if_small(q, required=True), F.lit(True))
    return both.select("q_id", "x_id", F.round(M.dot(F.col("qv"), F.col("xv")), 5).alias("dot"), F.round(M.cosine(F.col("qv"), F.col("xv")), 5).alias("cos"), F.round(M.l2(F.col("qv"), F.col("xv")), 5).alias("l2"))


@query(O.query([*PASSAGE, "b AS (SELECT max(f) AS m FROM xsets)"], "SELECT CAST(count(*) FILTER (a / (fx + fq - a) < a / (fq + m - a) - 1e-12 OR a / (fx + fq - a) > a / fq + 1e-12) AS BIGINT) AS violations FROM ov, b"))
def bounds_violations(spark: SparkSession, d: str) -> DataFrame:
    x, q = passages(spark, d)
    low, high = M.resemblance_bounds(F.col("a"), F.col("fq"), sets.padding_bound(x))
    r = M.resemblance(F.col("a"), F.col("fx"), F.col("fq"))
    return exact.overlaps(x, q).agg(F.count(F.when((r < low - 1e-12) | (r > high + 1e-12), 1)).alias("violations"))


@query(O.query([*PASSAGE, f"g2 AS ({O.top('ov', 'a', 2)})", "tri AS (SELECT a.q_id, a.x_id AS x1, b.x_id AS x2 FROM g2 a JOIN g2 b USING (q_id) WHERE a.rank = 1 AND b.rank = 2)", "three AS (SELECT q_id, count(*) AS n FROM tri JOIN qinc q ON q.id = q_id JOIN xinc x ON x.id = x1 AND x.e = q.e JOIN xinc y ON y.id = x2 AND y.e = q.e GROUP BY q_id)", "uni AS (SELECT q_id, count(DISTINCT e) AS u FROM (SELECT q_id, e FROM tri JOIN qinc ON id = q_id UNION ALL SELECT q_id, e FROM tri JOIN xinc ON id = x1 UNION ALL SELECT q_id, e FROM tri JOIN xinc ON id = x2) GROUP BY q_id)"], "SELECT q_id, x1, x2, round(coalesce(n, 0) / u, 6) AS value FROM tri JOIN uni USING (q_id) LEFT JOIN three USING (q_id)"))
def exact_threeway(spark: SparkSession, d: str) -> DataFrame:
    x, q = passages(spark, d)
    two = exact.exact_topk(x, q, 2, "overlap").groupBy("q_id").agg(F.max(F.when(F.col("rank") == 1, F.col("x_id"))).alias("x1"), F.max(F.when(F.col("rank") == 2, F.col("x_id"))).alias("x2")).where("x2 is not null")
    e = x.select("id", "elems")
    full = two.join(e.toDF("x1", "e1"), "x1").join(e.toDF("x2", "e2"), "x2").join(q.select(F.col("id").alias("q_id"), "elems"), "q_id")
    return full.select("q_id", "x1", "x2", F.round(M.resemblance3(F.col("elems"), F.col("e1"), F.col("e2")), 6).alias("value"))


# exact search


@query(O.query(PASSAGE, f"SELECT q_id, x_id, a FROM ({O.top('ov', 'a', 1)})"))
def mips_top1(spark: SparkSession, d: str) -> DataFrame:
    return exact.mips(*passages(spark, d))


@query(O.query(PASSAGE, f"SELECT q_id, true AS same FROM ({O.top('ov', 'a / fq', 1)})"))
def mcs_equals_mips(spark: SparkSession, d: str) -> DataFrame:
    x, q = passages(spark, d)
    return exact.mips(x, q).join(exact.mcs(x, q).select("q_id", F.col("x_id").alias("other")), "q_id").select("q_id", (F.col("x_id") == F.col("other")).alias("same"))


@query(O.query(PASSAGE, O.top("ov", "a / fq", 10)))
def gold_topk(spark: SparkSession, d: str) -> DataFrame:
    return exact.exact_topk(*passages(spark, d), 10)


@query(O.query(PASSAGE, "SELECT q_id, x_id, CAST(a AS BIGINT) AS a FROM ov WHERE a >= 20"))
def s0_near(spark: SparkSession, d: str) -> DataFrame:
    return exact.near_neighbors(*passages(spark, d), 20)


@query(O.query(PASSAGE, "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, round(a / fq, 6) AS value FROM ov"))
def linear_scan(spark: SparkSession, d: str) -> DataFrame:
    return exact.linear_scan(*passages(spark, d))


@query(O.query(PASSAGE, O.top("ov", "a", 10)))
def inverted_topk(spark: SparkSession, d: str) -> DataFrame:
    x, q = passages(spark, d)
    return exact.InvertedIndex(x).search(q, 10)


@query(O.query(PASSAGE, "SELECT q_id, x_id, CAST(a AS BIGINT) AS a FROM ov WHERE a >= ceil(0.5 * fq)"))
def inverted_prefix(spark: SparkSession, d: str) -> DataFrame:
    x, q = passages(spark, d)
    return exact.InvertedIndex(x).search_threshold(x, q, 0.5)


@query(O.query([*O.base("order_parts"), "big AS (SELECT e FROM inc GROUP BY e HAVING count(*) > 25)", "k AS (SELECT * FROM inc SEMI JOIN big USING (e))"], "SELECT a.e AS e1, b.e AS e2, CAST(count(*) AS BIGINT) AS n FROM k a JOIN k b ON a.id = b.id AND a.e < b.e GROUP BY a.e, b.e HAVING count(*) <= 1"))
def minimal_infrequent_pairs(spark: SparkSession, d: str) -> DataFrame:
    inc = collection(spark, d, "order_parts")
    return exact.minimal_infrequent_pairs(inc, 25).where("n <= 1")


def _touched_sql(coll: str) -> str:
    s = O.split(coll)
    return O.query([*s, "df AS (SELECT e, count(*) AS df FROM xinc GROUP BY e)"], f"SELECT '{coll}' AS collection, q.id AS q_id, CAST(any_value(f) AS BIGINT) AS fq, CAST(coalesce(sum(df), 0) AS BIGINT) AS touched FROM qinc q JOIN qsets USING (id) LEFT JOIN df USING (e) GROUP BY q.id")


@query(f"SELECT * FROM ({_touched_sql('order_parts')}) UNION ALL SELECT * FROM ({_touched_sql('docs_w')})")
def inverted_cost(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for coll in ("order_parts", "docs_w"):
        train, queries = sets.split_partitions(collection(spark, d, coll))
        one = exact.InvertedIndex(train).postings_touched(queries).select(F.lit(coll).alias("collection"), "q_id", "fq", "touched")
        out = one if out is None else out.unionByName(one)
    return out


@query(O.query([*PASSAGE, f"c AS ({O.top('ov', 'a / fq', 10)})", f"r AS ({O.top('ov', 'a / (fx + fq - a)', 10)})"], "SELECT q_id, CAST(count(r.x_id) AS BIGINT) AS shared FROM c LEFT JOIN r USING (q_id, x_id) GROUP BY q_id"))
def order_disagreement(spark: SparkSession, d: str) -> DataFrame:
    x, q = passages(spark, d)
    return exact.ranking_overlap(exact.exact_topk(x, q, 10, "containment"), exact.exact_topk(x, q, 10, "resemblance"))


# worked example

NAMES = {1: "five guys burgers and fries brooklyn new york", 2: "five kitchen berkley"}


@query("""SELECT * FROM (VALUES (1::BIGINT, 2::BIGINT, 8::BIGINT, 2::BIGINT, 0.25::DOUBLE, 1.0::DOUBLE, 0.25::DOUBLE, 0.142857::DOUBLE), (2, 1, 3, 2, 0.25, 0.5, 0.111111, 0.066667)) AS v(x_id, a, fx, fq, resemblance, containment, padded_one, padded_two)""")
def worked_example(spark: SparkSession, d: str) -> DataFrame:
    x = sets.word_sets(spark.createDataFrame(list(NAMES.items()), "i bigint, s string"), "i", "s")
    q = sets.word_sets(spark.createDataFrame([(0, "five guys")], "i bigint, s string"), "i", "s")
    m = sets.padding_bound(x)
    r = {"resemblance": M.resemblance(F.col("a"), F.col("fx"), F.col("fq")), "containment": M.containment(F.col("a"), F.col("fq")), "padded_one": M.sim_opm1(F.col("a"), F.col("fq"), m), "padded_two": M.sim_opm2(F.col("a"), m)}
    return exact.overlaps(x, q).select("x_id", "a", "fx", "fq", *[F.round(c, 6).alias(n) for n, c in r.items()])


# transformations: identities counted over all pairs, on padded rows

TURNS = [*O.split("turn_w"), O.OV]


def turns(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return sets.split_partitions(collection(spark, d, "turn_w"))


def _padded(spark: SparkSession, d: str, data, ask) -> DataFrame:
    x, q = turns(spark, d)
    m = sets.padding_bound(x, "data_and_query", q)
    px, pq = (s.select("id", "elems", F.col("padded_f").alias("f")) for s in (data(x, m), ask(q, m)))
    return exact.overlaps(px, pq).select("q_id", "x_id", "a", (F.col("fx") + F.col("fq") - F.col("a")).alias("whole"))


_MT = "mt AS (SELECT max(f) AS m FROM sets)"
add("transform_p1", lambda s, d: _padded(s, d, tr.pad_data_one, lambda q, m: tr.pad_query_none(q)), O.query([*TURNS, _MT], "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, CAST(m + fq - a AS BIGINT) AS whole FROM ov, mt"))
add("transform_p2", lambda s, d: _padded(s, d, lambda x, m: tr.pad_two_sided(x, m, "data"), lambda q, m: tr.pad_two_sided(q, m, "query")), O.query([*TURNS, _MT], "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, CAST(2 * m - a AS BIGINT) AS whole FROM ov, mt"))


@query(O.query([*TURNS, _MT], "SELECT q_id, x_id, round(a / (2 * m - a), 6) AS value FROM ov, mt"))
def transform_p3(spark: SparkSession, d: str) -> DataFrame:
    x, q = turns(spark, d)
    m = sets.padding_bound(x, "data_and_query", q)
    pairs = tr.weighted_pairs(tr.pad_weighted(x, m, "data"), tr.pad_weighted(q, m, "query"))
    return pairs.select("q_id", "x_id", F.round(F.col("low") / F.col("high"), 6).alias("value"))


@query(O.query([*WEIGHT_PAIRS, "mw AS (SELECT max(s) AS m FROM tot)"], "SELECT q_id, x_id, round(CAST(low AS DOUBLE) / (2 * m - low), 6) AS value FROM wp, mw"))
def transform_weighted(spark: SparkSession, d: str) -> DataFrame:
    x, q = weighted(spark, d)
    total = F.aggregate("weights", F.lit(0.0), lambda a, w: a + w)
    m = x.unionByName(q).agg(F.max(total)).first()[0]
    pairs = tr.weighted_pairs(tr.pad_weighted_real(x, m, "data"), tr.pad_weighted_real(q, m, "query"))
    return pairs.select("q_id", "x_id", F.round(F.col("low") / F.col("high"), 6).alias("value"))


def _augmented(spark: SparkSession, d: str, data, ask, scale, n: int) -> DataFrame:
    """Inner product and both norms of the augmented vectors of pairs that overlap.
    What is added to a vector depends on its size alone."""
    x, q = sets.split_partitions(kept(collection(spark, d, "turn_w"), "turn_w"))
    v = math.sqrt(sets.padding_bound(x, "data_and_query", q))
    s = scale(v)
    x, q = (side.withColumn("norm2", F.round(tr.augmented_norm2(F.col("f"), s, F.col("aug"), n), 6)) for side in (data(x, v), ask(q, v)))
    more = ("f", "norm2", "aug")
    return tiles.products(tiles.coded(x, "data", more=more), tiles.coded(q, "query", more=more), lambda a, xa, qa: tr.augmented_product(a, s, xa, qa, n))


_Z = "(0.83::DOUBLE * 0.83 / m)"
add(
    "transform_l2",
    lambda s, d: _augmented(s, d, lambda x, v: tr.augment_l2(x, 0.83, v, 3, "data"), lambda q, v: tr.augment_l2(q, 0.83, v, 3, "query"), lambda v: 0.83 / v, 6),
    O.query([*TURNS, _MT], f"SELECT q_id, x_id, round(a*{_Z} + 0.5*(fx*{_Z} + pow(fx*{_Z},2) + pow(fx*{_Z},4) + fq*{_Z} + pow(fq*{_Z},2) + pow(fq*{_Z},4)), 6) AS product, round(fx*{_Z} + pow(fx*{_Z},2) + pow(fx*{_Z},4) + pow(fx*{_Z},8) + 0.75, 6) AS norm2_x, round(fq*{_Z} + pow(fq*{_Z},2) + pow(fq*{_Z},4) + pow(fq*{_Z},8) + 0.75, 6) AS norm2_q FROM ov, mt"),
)
_Y = "(0.75::DOUBLE * 0.75 / m)"
add(
    "transform_sign",
    lambda s, d: _augmented(s, d, lambda x, v: tr.augment_sign(x, 0.75, v, 2, "data"), lambda q, v: tr.augment_sign(q, 0.75, v, 2, "query"), lambda v: 0.75 / v, 4),
    O.query([*TURNS, _MT], f"SELECT q_id, x_id, round(a*{_Y}, 6) AS product, round(0.5 + pow(fx*{_Y}, 4), 6) AS norm2_x, round(0.5 + pow(fq*{_Y}, 4), 6) AS norm2_q FROM ov, mt"),
)
add(
    "transform_norm",
    lambda s, d: _augmented(s, d, lambda x, v: tr.augment_norm(x, v, "data"), lambda q, v: tr.augment_norm(q, v, "query"), lambda v: 1 / v, 2),
    O.query([*TURNS, _MT], "SELECT q_id, x_id, round(a::DOUBLE / m, 6) AS product, 1.0::DOUBLE AS norm2_x, 1.0::DOUBLE AS norm2_q FROM ov, mt"),
)


def _padded_count(qpad: str, xpad: str) -> str:
    """Overlapping pairs whose count of common elements changes when the two sides are padded."""
    pad = lambda side, name: f"SELECT id, 'e' || CAST(e AS VARCHAR) AS e FROM {side}inc UNION ALL SELECT id, '{name}' || CAST(unnest(range(m - f)) AS VARCHAR) FROM {side}sets, mt" if name else f"SELECT id, 'e' || CAST(e AS VARCHAR) AS e FROM {side}inc"
    return f"SELECT count(*) AS n FROM (SELECT q.id AS q_id, x.id AS x_id, count(*) AS b FROM ({pad('q', qpad)}) q JOIN ({pad('x', xpad)}) x USING (e) GROUP BY q.id, x.id) FULL JOIN ov USING (q_id, x_id) WHERE a IS DISTINCT FROM b"


@query(O.query([*TURNS, _MT], f"SELECT CAST((SELECT n FROM ({_padded_count('', 'A')})) + (SELECT n FROM ({_padded_count('B', 'A')})) AS BIGINT) AS violations"))
def inner_product_preserved(spark: SparkSession, d: str) -> DataFrame:
    """Pairs whose overlap differs before and after padding, under both pairs of maps."""
    x, q = sets.split_partitions(kept(collection(spark, d, "turn_w"), "turn_w"))
    m = sets.padding_bound(x, "data_and_query", q)
    two = lambda s, side: tr.pad_two_sided(s, m, side).select("id", F.col("elems").alias("two"))
    padded = tr.pad_data_one(x, m).select("id", F.col("elems").alias("one")).join(two(x, "data"), "id")
    data = tiles.coded(x.join(padded, "id"), "data", more=("one", "two"))
    ask = tiles.coded(q.join(tr.pad_query_none(q).select("id", F.col("elems").alias("one")), "id").join(two(q, "query"), "id"), "query", more=("one", "two"))
    return tiles.changed_counts(data, ask, (("one", "one"), ("two", "two"))).agg(F.coalesce(F.sum("n"), F.lit(0).cast("bigint")).alias("violations"))


# theory

RATIOS = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 0.95)


def grid(spark: SparkSession, steps: int = 99) -> DataFrame:
    """``s0_over_m, c``."""
    c = spark.range(1, steps + 1).select((F.col("id") / (steps + 1)).alias("c"))
    return c.select(F.explode(F.array(*[F.lit(x) for x in RATIOS])).alias("s0_over_m"), "c")


#: Overlaps and sizes that benchmark passages and documents have, with c in steps of a hundredth.
SEEN = [*PASSAGE, "mm AS (SELECT max(f) AS m FROM xsets)", "seen AS (SELECT DISTINCT a::DOUBLE AS a, fq::DOUBLE AS fq, m::DOUBLE AS m FROM ov, mm WHERE fq <= m)", "steps AS (SELECT i / 100.0::DOUBLE AS c FROM (SELECT unnest(range(1, 100)) AS i))", "grid AS (SELECT DISTINCT a / m AS s0_over_m, c FROM seen, steps WHERE a < m)"]


def seen(spark: SparkSession, d: str) -> DataFrame:
    """``a, fq, m``: what pairs of a passage and a document have, M being the largest document."""
    x, q = passages(spark, d)
    m = sets.padding_bound(x)
    return exact.overlaps(x, q).where(F.col("fq") <= m).select(F.col("a").cast("double").alias("a"), F.col("fq").cast("double").alias("fq"), F.lit(float(m)).alias("m")).distinct()


def steps(spark: SparkSession) -> DataFrame:
    return F.broadcast(spark.range(1, 100).select((F.col("id") / 100).alias("c")))


def seen_grid(spark: SparkSession, d: str) -> DataFrame:
    """``s0_over_m, c`` of the overlaps that occur."""
    return seen(spark, d).where("a < m").select((F.col("a") / F.col("m")).alias("s0_over_m")).distinct().crossJoin(steps(spark))


GRID = "grid AS (SELECT s AS s0_over_m, i / 100.0::DOUBLE AS c FROM (SELECT unnest([" + ",".join(map(str, RATIOS)) + "]::DOUBLE[]) AS s), (SELECT unnest(range(1, 100)) AS i))"
ACOS = "(1 - acos({}) / pi())"


def _curve(name: str, ps, sql1: str, sql2: str) -> None:
    add(name, lambda spark, d: seen_grid(spark, d).select("s0_over_m", "c", F.round(T.rho_col(*ps()), 6).alias("rho")), O.query(SEEN, f"SELECT s0_over_m, c, round(ln({sql1}) / ln({sql2}), 6) AS rho FROM grid"))


_curve("rho_opm", lambda: (F.col("s0_over_m") / (2 - F.col("s0_over_m")), F.col("c") * F.col("s0_over_m") / (2 - F.col("c") * F.col("s0_over_m"))), "s0_over_m / (2 - s0_over_m)", "c * s0_over_m / (2 - c * s0_over_m)")
_curve("rho_sign", lambda: (T.srp_col(F.col("s0_over_m")), T.srp_col(F.col("c") * F.col("s0_over_m"))), ACOS.format("s0_over_m"), ACOS.format("c * s0_over_m"))


@query(O.query(SEEN, f"SELECT s0_over_m, c, round(ln(s0_over_m / (2 - s0_over_m)) / ln(c * s0_over_m / (2 - c * s0_over_m)), 6) AS rho_opm, round(ln({ACOS.format('s0_over_m')}) / ln({ACOS.format('c * s0_over_m')}), 6) AS rho_sign FROM grid"))
def rho_curves(spark: SparkSession, d: str) -> DataFrame:
    return seen_grid(spark, d).select("s0_over_m", "c", F.round(T.rho_col(F.col("s0_over_m") / (2 - F.col("s0_over_m")), F.col("c") * F.col("s0_over_m") / (2 - F.col("c") * F.col("s0_over_m"))), 6).alias("rho_opm"), F.round(T.rho_col(T.srp_col(F.col("s0_over_m")), T.srp_col(F.col("c") * F.col("s0_over_m"))), 6).alias("rho_sign"))


FQ0, M0 = 60.0, 200.0  # a query's size and the bound for the plans at a known size


def _known(name: str, far, sql: str) -> None:
    """Exponents at the passages' own sizes, for overlaps below both sizes."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        near = F.col("a") / (F.col("fq") + F.col("m") - F.col("a"))
        return seen(spark, d).where("a < m and a < fq + m - a").crossJoin(steps(spark)).select("a", "fq", "c", F.round(T.rho_col(near, far(F.col("c") * F.col("a"))), 6).alias("rho"))

    add(name, run, O.query(SEEN, f"SELECT a, fq, c, round(ln(a / (fq + m - a)) / ln({sql}), 6) AS rho FROM seen, steps WHERE a < m AND a < fq + m - a"))


_known("rho_opm_q", lambda s: s / (F.col("fq") + F.col("m") - s), "c * a / (fq + m - c * a)")
_known("rho_minhash_q", lambda s: s / F.col("fq"), "c * a / fq")


@query(O.query([*SEEN, "u AS (SELECT count(DISTINCT e)::DOUBLE AS d FROM xinc)", "s AS (SELECT DISTINCT a FROM seen)"], "SELECT a, c, round(ln((1 - 1 / 64.0::DOUBLE) * a / d + 1 / 64.0::DOUBLE) / ln((1 - 1 / 64.0::DOUBLE) * c * a / d + 1 / 64.0::DOUBLE), 6) AS rho FROM s, steps, u WHERE a < d"))
def rho_sampling(spark: SparkSession, d: str) -> DataFrame:
    """In the documents' universe of words, with 64 miss values."""
    u = sets.incidence(passages(spark, d)[0]).agg(F.countDistinct("e").cast("double").alias("d"))
    p = lambda s: (1 - F.lit(1 / 64)) * s / F.col("d") + F.lit(1 / 64)
    full = seen(spark, d).select("a").distinct().crossJoin(steps(spark)).crossJoin(F.broadcast(u)).where("a < d")
    return full.select("a", "c", F.round(T.rho_col(p(F.col("a")), p(F.col("c") * F.col("a"))), 6).alias("rho"))


@query()
def rho_l2alsh(spark: SparkSession, d: str) -> DataFrame:
    """Best exponents over the grid of (m, U, r), at the overlaps that occur."""

    def run(batches):
        for batch in batches:
            rows = [(s, c, best[0], *best[1:]) for s in batch.column(0).to_pylist() for c in (0.3, 0.5, 0.7, 0.9) if (best := T.rho_l2alsh(s, c))]
            cols = list(zip(*rows, strict=True)) or [()] * 6
            kinds = (pa.float64(), pa.float64(), pa.float64(), pa.int32(), pa.float64(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(cols, kinds, strict=True)], names=["s0_over_m", "c", "rho", "m", "u", "r"])

    some = seen(spark, d).where("a < m").select((F.col("a") / F.col("m")).alias("s0_over_m")).distinct().repartition("s0_over_m")
    return some.mapInArrow(run, "s0_over_m double, c double, rho double, m int, u double, r double").withColumn("rho", F.round("rho", 6))


_US = "[" + ",".join(str(round(0.3 + 0.02 * i, 2)) for i in range(35)) + "]::DOUBLE[]"
_SIGN_GRID = [GRID, f"par AS (SELECT m, u, pow(m / (4 * (pow(2, m) - 1)), pow(2.0::DOUBLE, -m)) AS peak FROM (SELECT unnest(range(1, 6)) AS m), (SELECT unnest({_US}) AS u))", "z AS (SELECT s0_over_m, c, m, u, s0_over_m * u * u AS z, least(c * s0_over_m * u * u, peak) AS y FROM grid, par)", "far AS (SELECT s0_over_m, c, 1 - acos(z / (m / 4.0::DOUBLE + pow(u, pow(2, m + 1)))) / pi() AS p1, 1 - acos(y / (m / 4.0::DOUBLE + pow(y, pow(2, m)))) / pi() AS p2 FROM z WHERE z / (m / 4.0::DOUBLE + pow(u, pow(2, m + 1))) <= 1)"]


@query(O.query(_SIGN_GRID, "SELECT s0_over_m, c, round(min(ln(p1) / ln(p2)), 6) AS rho FROM far WHERE p1 > 0 AND p1 < 1 AND p2 > 0 AND p2 < 1 GROUP BY s0_over_m, c"))
def rho_signalsh(spark: SparkSession, d: str) -> DataFrame:
    """The parameter search as a frame: one row a (U, m), the least exponent per (S0, c)."""
    par = [(m, u, (m / (4 * (2**m - 1))) ** (2.0**-m)) for m in range(1, 6) for u in [round(0.3 + 0.02 * i, 2) for i in range(35)]]
    p = spark.createDataFrame(par, "m int, u double, peak double")
    full = grid(spark).crossJoin(F.broadcast(p))
    z = F.col("s0_over_m") * F.col("u") * F.col("u")
    y = F.least(F.col("c") * z, F.col("peak"))
    quarter = F.col("m") / 4
    near = z / (quarter + F.pow("u", F.pow(F.lit(2.0), F.col("m") + 1)))
    far = y / (quarter + F.pow(y, F.pow(F.lit(2.0), F.col("m"))))
    return full.where(near <= 1).select("s0_over_m", "c", T.rho_col(T.srp_col(near), T.srp_col(far)).alias("r")).where("r is not null").groupBy("s0_over_m", "c").agg(F.round(F.min("r"), 6).alias("rho"))


@query(O.query([GRID, "g AS (SELECT c, fq, m, s0_over_m * least(fq, m) AS s0 FROM grid, (SELECT unnest([5, 20, 60]::DOUBLE[]) AS fq), (SELECT unnest([20, 60, 200, 2000]::DOUBLE[]) AS m))", "r AS (SELECT ln(s0 / (fq + m - s0)) / ln(c * s0 / (fq + m - c * s0)) AS ours, ln(s0 / (fq + m - s0)) / ln(c * s0 / fq) AS theirs FROM g)"], "SELECT CAST(count(*) FILTER (ours > theirs + 1e-12) AS BIGINT) AS violations FROM r"))
def theorem4_violations(spark: SparkSession, d: str) -> DataFrame:
    """Grid points where the padded exponent at a known query size exceeds minhash's."""
    g = grid(spark).crossJoin(spark.createDataFrame([(f, float(m)) for f in (5.0, 20.0, 60.0) for m in (20, 60, 200, 2000)], "fq double, m double"))
    s0 = F.col("s0_over_m") * F.least("fq", "m")
    near = s0 / (F.col("fq") + F.col("m") - s0)
    ours, theirs = T.rho_col(near, F.col("c") * s0 / (F.col("fq") + F.col("m") - F.col("c") * s0)), T.rho_col(near, F.col("c") * s0 / F.col("fq"))
    return g.select(ours.alias("a"), theirs.alias("b")).agg(F.count(F.when(F.col("a") > F.col("b") + 1e-12, 1)).alias("violations"))


#: 1, 1*3, 1*3*5, ...: the normal integral from 0 to x is the density at x times the sum of x^(2i-1) over these.
_ODD = [float(math.prod(range(1, 2 * i, 2))) for i in range(1, 31)]


@query(O.query([*PASSAGE, "dist AS (SELECT DISTINCT sqrt(fx + fq - 2 * a) AS d FROM ov WHERE fx + fq - 2 * a > 0)"], f"SELECT r, d, round(1 - 2 * phi - 2 * d / (r * sqrt(2 * pi())) * (1 - exp(-r * r / (2 * d * d))), 5) AS p FROM (SELECT r, d, 0.5 - exp(-pow(r / d, 2) / 2) / sqrt(2 * pi()) * list_sum(list_transform({_ODD}::DOUBLE[], lambda v, i: pow(r / d, 2 * i - 1) / v)) AS phi FROM (SELECT unnest([1.0, 2.5]::DOUBLE[]) AS r), dist)"))
def law_l2(spark: SparkSession, d: str) -> DataFrame:
    """At the distances of passages and documents that are not equal."""
    apart = exact.overlaps(*passages(spark, d)).select(F.sqrt(F.col("fx") + F.col("fq") - 2 * F.col("a")).alias("d")).where("d > 0").distinct()

    def run(batches):
        for batch in batches:
            rows = [(r, x, T.f_r(x, r)) for x in batch.column(0).to_pylist() for r in (1.0, 2.5)]
            cols = list(zip(*rows, strict=True)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.float64()) for v in cols], names=["r", "d", "p"])

    return apart.mapInArrow(run, "r double, d double, p double").withColumn("p", F.round("p", 5))


@query(O.query(PASSAGE, "SELECT q_id, x_id, round(1 - acos(least(1.0::DOUBLE, a / sqrt(fx * fq))) / pi(), 6) AS p FROM ov"))
def law_srp(spark: SparkSession, d: str) -> DataFrame:
    return exact.overlaps(*passages(spark, d)).select("q_id", "x_id", F.round(T.srp_col(M.cosine_sets(F.col("a"), F.col("fx"), F.col("fq"))), 6).alias("p"))


@query(O.query(PASSAGE, "SELECT q_id, x_id, round(a / (fx + fq - a), 6) AS p FROM ov"))
def law_minhash(spark: SparkSession, d: str) -> DataFrame:
    return exact.overlaps(*passages(spark, d)).select("q_id", "x_id", F.round(M.resemblance(F.col("a"), F.col("fx"), F.col("fq")), 6).alias("p"))


@query(O.query([*PASSAGE, "u AS (SELECT count(DISTINCT e)::DOUBLE AS d FROM xinc)"], "SELECT q_id, x_id, round(a / d + (1 - a / d) / 4, 6) AS printed, round(a / d + (1 - (fx + fq - a) / d) / 4, 6) AS exact FROM ov, u"))
def law_sampling(spark: SparkSession, d: str) -> DataFrame:
    """Both laws of each passage and document, in the documents' universe of words with 4 miss values."""
    x, q = passages(spark, d)
    u = sets.incidence(x).agg(F.countDistinct("e").cast("double").alias("d"))
    share = F.col("a") / F.col("d")
    return exact.overlaps(x, q).crossJoin(F.broadcast(u)).select("q_id", "x_id", F.round(share + (1 - share) / 4, 6).alias("printed"), F.round(share + (1 - (F.col("fx") + F.col("fq") - F.col("a")) / F.col("d")) / 4, 6).alias("exact"))


def _plan_rows() -> list[tuple]:
    rows = []
    for scheme, p in {"minhash": lambda a: None, "opm1": lambda a: T.opm1(a, FQ0, M0), "opm2": lambda a: T.opm2(a, M0), "normsign": lambda a: T.srp(a / M0), "sampling": lambda a: T.sampling(a, 0, 0, 70_000, 64)}.items():
        for s0 in (20.0, 40.0, 60.0):
            for c in (0.5, 0.8):
                p1, p2 = (s0 / (FQ0 + M0 - s0), c * s0 / FQ0) if scheme == "minhash" else (p(s0), p(c * s0))
                rows.append((scheme, s0, c, p1, p2))
    return rows


_PLAN = "pl AS (SELECT scheme, s0, c, CASE scheme WHEN 'minhash' THEN s0 / (260 - s0) WHEN 'opm1' THEN s0 / (260 - s0) WHEN 'opm2' THEN s0 / (400 - s0) WHEN 'normsign' THEN 1 - acos(s0 / 200) / pi() ELSE s0 / 70000 + (1 - s0 / 70000) / 64 END AS p1, CASE scheme WHEN 'minhash' THEN c * s0 / 60 WHEN 'opm1' THEN c * s0 / (260 - c * s0) WHEN 'opm2' THEN c * s0 / (400 - c * s0) WHEN 'normsign' THEN 1 - acos(c * s0 / 200) / pi() ELSE c * s0 / 70000 + (1 - c * s0 / 70000) / 64 END AS p2 FROM (SELECT unnest(['minhash','opm1','opm2','normsign','sampling']) AS scheme), (SELECT unnest([20,40,60]::DOUBLE[]) AS s0), (SELECT unnest([0.5,0.8]::DOUBLE[]) AS c))"


@query(O.query([_PLAN], "SELECT scheme, s0, c, round(p1, 6) AS p1, round(p2, 6) AS p2, round(ln(p1) / ln(p2), 6) AS rho FROM pl"))
def sensitivity_table(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(s, s0, c, round(p1, 6), round(p2, 6), round(T.rho(p1, p2), 6)) for s, s0, c, p1, p2 in _plan_rows()], "scheme string, s0 double, c double, p1 double, p2 double, rho double")


#: Collision chances of every scheme at the overlaps and sizes that occur, for as many sets as there are.
_OWN_PLAN = [*SEEN, "nn AS (SELECT count(*)::DOUBLE AS n FROM xsets)", "u AS (SELECT count(DISTINCT e)::DOUBLE AS d FROM xinc)", "cc AS (SELECT unnest([0.5, 0.8]::DOUBLE[]) AS c)", "pl AS (SELECT *, CASE scheme WHEN 'minhash' THEN s0 / (fq + m - s0) WHEN 'opm1' THEN s0 / (fq + m - s0) WHEN 'opm2' THEN s0 / (2 * m - s0) WHEN 'normsign' THEN 1 - acos(s0 / m) / pi() ELSE s0 / d + (1 - s0 / d) / 64 END AS p1, CASE scheme WHEN 'minhash' THEN c * s0 / fq WHEN 'opm1' THEN c * s0 / (fq + m - c * s0) WHEN 'opm2' THEN c * s0 / (2 * m - c * s0) WHEN 'normsign' THEN 1 - acos(c * s0 / m) / pi() ELSE c * s0 / d + (1 - c * s0 / d) / 64 END AS p2 FROM (SELECT a AS s0, fq, m FROM seen WHERE a < m), (SELECT unnest(['minhash','opm1','opm2','normsign','sampling']) AS scheme), cc, nn, u WHERE n > 1 AND s0 < d)"]


def own_plans(spark: SparkSession, d: str) -> DataFrame:
    """``scheme, s0, fq, c, n, p1, p2``."""
    x = passages(spark, d)[0]
    s0, fq, m, u = F.col("a"), F.col("fq"), F.col("m"), F.col("d")
    sizes = x.where("f > 0").agg(F.count("*").cast("double").alias("n")).crossJoin(sets.incidence(x).agg(F.countDistinct("e").cast("double").alias("d")))
    full = seen(spark, d).where("a < m").crossJoin(F.broadcast(sizes)).where("n > 1 and a < d").withColumn("c", F.explode(F.array(F.lit(0.5), F.lit(0.8))))
    far = F.col("c") * s0
    laws = {"minhash": lambda s: s / (fq + m - s), "opm1": lambda s: s / (fq + m - s), "opm2": lambda s: s / (2 * m - s), "normsign": lambda s: T.srp_col(s / m), "sampling": lambda s: s / u + (1 - s / u) / 64}
    made = F.explode(F.array(*[F.struct(F.lit(k).alias("scheme"), p(s0).alias("p1"), (far / fq if k == "minhash" else p(far)).alias("p2")) for k, p in laws.items()]))
    return full.select(s0.alias("s0"), "fq", "c", "n", made.alias("x")).select("x.scheme", "s0", "fq", "c", "n", "x.p1", "x.p2")


@query(O.query(_OWN_PLAN, "SELECT scheme, s0, fq, c, round(log10(pow(n, ln(p1) / ln(p2)) * ln(n) / -ln(p2)), 6) AS log10_query_cost, round(log10(pow(n, 1 + ln(p1) / ln(p2))), 6) AS log10_space FROM pl"))
def cost_model(spark: SparkSession, d: str) -> DataFrame:
    n, r = F.col("n"), T.rho_col(F.col("p1"), F.col("p2"))
    return own_plans(spark, d).select("scheme", "s0", "fq", "c", F.round(F.log10(F.pow(n, r) * F.log(n) / -F.log("p2")), 6).alias("log10_query_cost"), F.round(F.log10(F.pow(n, 1 + r)), 6).alias("log10_space"))


@query(O.query([*_OWN_PLAN, "kk AS (SELECT *, greatest(1, ceil(ln(n) / -ln(p2))) AS k FROM pl WHERE scheme IN ('opm1', 'opm2') AND s0 >= 0.9 * fq)"], "SELECT scheme, s0, fq, c, CAST(k AS INT) AS k, ceil(ln(10.0::DOUBLE) / pow(p1, k)) AS l FROM kk"))
def plan_kl(spark: SparkSession, d: str) -> DataFrame:
    """(K, L) for pairs of containment 0.9; L is a double, for it can exceed 64 bits."""
    k = F.greatest(F.lit(1.0), F.ceil(F.log("n") / -F.log("p2")).cast("double"))
    wanted = own_plans(spark, d).where("scheme in ('opm1', 'opm2') and s0 >= 0.9D * fq").withColumn("k", k)
    tables = F.lit(math.log(10)) / F.pow("p1", F.col("k"))
    return wanted.select("scheme", "s0", "fq", "c", F.col("k").cast("int").alias("k"), F.when(tables < 2.0**52, F.ceil(tables).cast("double")).otherwise(tables).alias("l"))


@query(O.query([*PASSAGE, "kl AS (SELECT unnest([1,2,3]) AS k, unnest([4,16,64]) AS l)"], f"SELECT k, l, round(sum(1 - pow(1 - pow(a / ({BOUND} + fq - a), k), l)) / ((SELECT count(*) FROM xsets) * (SELECT count(*) FROM qsets)), 6) AS expected_fraction FROM ov, kl GROUP BY k, l"))
def expected_scan(spark: SparkSession, d: str) -> DataFrame:
    """Expected share of sets that (K, L) reports, from the padded law."""
    x, q = passages(spark, d)
    pairs = x.where("f > 0").count() * q.where("f > 0").count()
    kl = F.broadcast(spark.createDataFrame([(1, 4), (2, 16), (3, 64)], "k int, l int"))
    p = M.sim_opm1(F.col("a"), F.col("fq"), BOUND)
    return exact.overlaps(x, q).crossJoin(kl).groupBy("k", "l").agg(F.round(F.sum(1 - F.pow(1 - F.pow(p, F.col("k")), F.col("l"))) / F.lit(pairs), 6).alias("expected_fraction"))


@query(O.query([*PASSAGE], f"SELECT round(avg(CASE WHEN a >= 0.5 * fq THEN a / ({BOUND} + fq - a) END) - avg(CASE WHEN a < 0.25 * fq THEN a / ({BOUND} + fq - a) END), 6) AS opm1_gap, round(avg(CASE WHEN a >= 0.5 * fq THEN a / (fx + fq - a) END) - avg(CASE WHEN a < 0.25 * fq THEN a / (fx + fq - a) END), 6) AS minhash_gap FROM ov"))
def collision_gap(spark: SparkSession, d: str) -> DataFrame:
    """Mean collision probability of good pairs less that of bad ones."""
    good, bad = F.col("a") >= F.lit(0.5) * F.col("fq"), F.col("a") < F.lit(0.25) * F.col("fq")
    gap = lambda p: F.round(F.avg(F.when(good, p)) - F.avg(F.when(bad, p)), 6)
    return exact.overlaps(*passages(spark, d)).agg(gap(M.sim_opm1(F.col("a"), F.col("fq"), BOUND)).alias("opm1_gap"), gap(M.resemblance(F.col("a"), F.col("fx"), F.col("fq"))).alias("minhash_gap"))
