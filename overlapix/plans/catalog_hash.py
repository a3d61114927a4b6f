"""Registered queries: signatures, laws, ranking, bucketing and the experiments."""

from __future__ import annotations

import math
from functools import partial

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from overlapix.functions import hashing as H
from overlapix.functions import measures as M
from overlapix.operators import bucketing, exact, ranking, schemes, sets, tiles
from overlapix.plans import oracle as O
from overlapix.plans import planner
from overlapix.plans.catalog_sets import PASSAGE, passages, weighted
from overlapix.plans.registry import add, query
from overlapix.sources.tables import collection, kept, load

SEED = 17
#: Codes of a signature query, of a ranking and of an index.
N_SIG, N_RANK = 8, 64
K, L = 2, 12
KINDS = ("minhash", "opm1", "opm2", "srp", "l2lsh", "l2alsh", "signalsh", "normsign")
PARAMS = {"srp2": {"width": 0.75}, "l2lsh": {"r": 2.5}, "l2alsh": {"u": 0.83, "m": 3, "r": 2.5}, "signalsh": {"u": 0.75, "m": 2}}


def scheme(kind: str, h: int, m: int, seed: int = SEED) -> schemes.Scheme:
    v = math.sqrt(m)
    return {
        "minhash": lambda: schemes.minhash(h, seed), "opm1": lambda: schemes.opm1(h, seed, m), "opm2": lambda: schemes.opm2(h, seed, m),
        "srp": lambda: schemes.srp(h, seed), "srp2": lambda: schemes.srp(h, seed, bits=2), "l2lsh": lambda: schemes.l2lsh(h, seed),
        "l2alsh": lambda: schemes.l2_alsh(h, seed, v), "signalsh": lambda: schemes.sign_alsh(h, seed, v), "normsign": lambda: schemes.norm_sign_alsh(h, seed, v),
    }[kind]()


def halves(spark: SparkSession, d: str, coll: str) -> tuple[DataFrame, DataFrame, int]:
    train, queries = sets.split_partitions(kept(collection(spark, d, coll).where("f > 0"), coll))
    return train, queries, sets.padding_bound(train, "data_and_query", queries)


# signatures


def _signature(kind: str, name: str) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        train, queries, m = halves(spark, d, "docs_w")
        s = scheme(kind, N_SIG, m)
        sides = [schemes.long_codes(sig, s).withColumn("side", F.lit(side)) for sig, side in ((s.data_signatures(train), "data"), (s.query_signatures(queries), "query"))]
        return sides[0].unionByName(sides[1])

    cols = "id, CAST(t AS INT) AS t, code" + (", from_pad" if kind in ("opm1", "opm2") else "")
    add(name, run, O.query([*O.split("docs_w"), *O.coded(kind, PARAMS.get(kind, {}), N_SIG, SEED)], f"SELECT {cols}, 'data' AS side FROM xcode UNION ALL SELECT {cols}, 'query' FROM qcode"))


for _kind in (*KINDS, "srp2"):
    _signature(_kind, {"srp2": "srp_2bit"}.get(_kind, f"{_kind}_signature"))


@query(O.query([*O.split("docs_w"), O.draws(N_SIG, SEED), O.bound(), O.pads(H.PAD_A, "padA")], f"SELECT id, CAST(t AS INT) AS t, code FROM ({O.codes('opm1', 'data', {})[1]})"))
def opm1_explicit(spark: SparkSession, d: str) -> DataFrame:
    """Padding by lists of pad hashes, without the staircase."""
    train, _, m = halves(spark, d, "docs_w")
    return schemes.long_codes(schemes.opm1(N_SIG, SEED, m, explicit=True).data_signatures(train))


@query(O.query([*O.split("docs_w"), O.draws(N_SIG, SEED), O.bound(), O.pads(H.PAD_A, "padA")], "SELECT CAST(t AS INT) AS t, CAST(min(n) AS BIGINT) AS m_from, low AS pad_min FROM padA GROUP BY t, low"))
def pad_staircase(spark: SparkSession, d: str) -> DataFrame:
    return schemes.staircase_frame(spark, N_SIG, halves(spark, d, "docs_w")[2], SEED)


@query(O.query([*O.split("docs_w"), O.draws(N_SIG, SEED), "mm AS (SELECT 3000 AS m)", O.pads(H.PAD_A, "padA")], f"SELECT id, CAST(t AS INT) AS t, code FROM ({O.codes('opm1', 'data', {})[1]})"))
def opm1_regrown(spark: SparkSession, d: str) -> DataFrame:
    """A larger bound out of stored raw signatures."""
    train, _, _ = halves(spark, d, "docs_w")
    raw = schemes.minhash(N_SIG, SEED).data_signatures(train)
    return schemes.long_codes(schemes.repad(raw, schemes.opm1(N_SIG, SEED, 3000)))


EMB = O.split("emb_bin")


def universe() -> list[int]:
    return [H.py_fp(str(i)) for i in range(64)]


_UNI = "uni AS (SELECT [" + ",".join(str(H.py_fp(str(i))) for i in range(64)) + "] AS u)"
_HIT = "SELECT s.id, t, (list_contains(el, u[a1 % 64 + 1])) AS hit FROM (SELECT id, list(e) AS el FROM {i} GROUP BY id) s CROSS JOIN hp CROSS JOIN uni"


def _sampled(spark: SparkSession, d: str, make) -> DataFrame:
    train, queries, _ = halves(spark, d, "emb_bin")
    s = make()
    return schemes.long_codes(s.data_signatures(train)).withColumn("side", F.lit("data")).unionByName(schemes.long_codes(s.query_signatures(queries)).withColumn("side", F.lit("query")))


def _sampling_sql(low: int = 0) -> str:
    parts = []
    for side, i in (("data", "xinc"), ("query", "qinc")):
        own = f"(SELECT DISTINCT id, {O.fp(repr(side + ':') + ' || CAST(id AS VARCHAR)')} AS e FROM {i})"
        parts.append(f"SELECT h.id, CAST(h.t AS INT) AS t, CASE WHEN hit THEN 0 ELSE {low} + m.h % 64 END AS code, '{side}' AS side FROM ({_HIT.format(i=i)}) h JOIN (SELECT id, t, h FROM {O.hashed(own)}) m ON m.id = h.id AND m.t = h.t")
    return O.query([*EMB, O.draws(N_SIG, SEED), _UNI], " UNION ALL ".join(parts))


add("sampling_lsh", lambda s, d: _sampled(s, d, lambda: schemes.sampling(N_SIG, SEED, universe(), 64)), _sampling_sql())
add("sampling_lsh_one_to_n", lambda s, d: _sampled(s, d, lambda: schemes.sampling(N_SIG, SEED, universe(), 64, "one_to_n")), _sampling_sql(1))
add("bit_sampling", lambda s, d: _sampled(s, d, lambda: schemes.bit_sampling(N_SIG, SEED, universe())), O.query([*EMB, O.draws(N_SIG, SEED), _UNI], " UNION ALL ".join(f"SELECT id, CAST(t AS INT) AS t, CAST(hit AS BIGINT) AS code, '{s}' AS side FROM ({_HIT.format(i=i)})" for s, i in (("data", "xinc"), ("query", "qinc")))))


@query(O.query([*O.base("docs_w"), O.draws(1, SEED), f"b AS (SELECT id, h % 16 AS bin, min(h // 16) AS v FROM {O.hashed('inc')} GROUP BY id, h % 16)", "want AS (SELECT id, t FROM sets, (SELECT unnest(range(16)) AS t))"], "SELECT id, CAST(t AS INT) AS t, arg_min(v, (bin - t + 16) % 16) + min((bin - t + 16) % 16) * 4294967296 AS code FROM want JOIN b USING (id) GROUP BY id, t"))
def oph_signature(spark: SparkSession, d: str) -> DataFrame:
    return schemes.long_codes(schemes.one_permutation(16, SEED).data_signatures(collection(spark, d, "docs_w").where("f > 0")))


@query()
def opmw_signature(spark: SparkSession, d: str) -> DataFrame:
    train, _, m = halves(spark, d, "turn_w")
    return schemes.long_codes(schemes.weighted_signatures(schemes.as_weighted(train), schemes.opmw(N_SIG, SEED, m)))


@query()
def cws_signature(spark: SparkSession, d: str) -> DataFrame:
    return schemes.long_codes(schemes.weighted_signatures(weighted(spark, d)[0], schemes.cws(N_SIG, SEED)))


@query()
def weighted_opm(spark: SparkSession, d: str) -> DataFrame:
    x, q = weighted(spark, d)
    m = x.unionByName(q).agg(F.max(F.aggregate("weights", F.lit(0.0), lambda a, w: a + w))).first()[0]
    return schemes.long_codes(schemes.weighted_signatures(x, schemes.weighted_opm(N_SIG, SEED, m)))


_RAW_EMB = [*O.base("emb_bin"), O.draws(32, SEED), f"code AS MATERIALIZED ({O.raw('inc')})"]


@query(O.query([*_RAW_EMB, "tri AS (SELECT id AS a, id + 1 AS b, id + 2 AS c FROM sets)"], "SELECT a AS id, CAST(count(*) AS BIGINT) AS matches FROM tri JOIN code x ON x.id = a JOIN code y ON y.id = b AND y.t = x.t JOIN code z ON z.id = c AND z.t = x.t WHERE x.code = y.code AND y.code = z.code GROUP BY a"))
def threeway_minhash(spark: SparkSession, d: str) -> DataFrame:
    """Agreements of three neighbours by id on all three codes."""
    sig = schemes.minhash(32, SEED).data_signatures(collection(spark, d, "emb_bin")).select("id", "sig")
    x, y, z = sig.toDF("id", "x"), sig.select((F.col("id") - 1).alias("id"), F.col("sig").alias("y")), sig.select((F.col("id") - 2).alias("id"), F.col("sig").alias("z"))
    same = F.zip_with(F.zip_with("x", "y", lambda a, b: F.when(a == b, a)), F.col("z"), lambda a, b: F.coalesce((a == b).cast("int"), F.lit(0)))
    counted = x.join(y, "id").join(z, "id").select("id", F.aggregate(same, F.lit(0).cast("bigint"), lambda s, v: s + v).alias("matches"))
    return counted.where("matches > 0")


@query()
def ml_minhash_join(spark: SparkSession, d: str) -> DataFrame:
    """The library's own minhash join, beside ours: pairs at distance under a half."""
    from pyspark.ml.feature import MinHashLSH
    from pyspark.ml.functions import array_to_vector

    on = F.transform("embedding", lambda v: (v > 0).cast("double"))
    df = load(spark, d, "embeddings").where(F.exists("embedding", lambda v: v > 0)).select(F.col("vec_id").alias("id"), array_to_vector(on).alias("v"))
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=4, seed=SEED).fit(df)
    return model.approxSimilarityJoin(df, df, 0.5, "dist").where("datasetA.id < datasetB.id").select(F.col("datasetA.id").alias("id1"), F.col("datasetB.id").alias("id2"), F.round("dist", 6).alias("dist"))


# laws against measurements: squared error of match rates, summed over all pairs


#: The laws on arrays of overlaps, sizes of sets and of queries.
ARRAY_LAWS = {
    "minhash": lambda a, fx, fq, m: a / (fx + fq - a),
    "opm1": lambda a, fx, fq, m: a / (m + fq - a),
    "opm2": lambda a, fx, fq, m: a / (2 * m - a),
    "srp": lambda a, fx, fq, m: 1 - np.arccos(a / np.sqrt(fx * fq)) / math.pi,
    "normsign": lambda a, fx, fq, m: 1 - np.arccos(a / m) / math.pi,
}


def _law(kind: str) -> None:
    h = 128

    def run(spark: SparkSession, d: str) -> DataFrame:
        train, queries, m = halves(spark, d, "emb_bin")
        s = scheme(kind, h, m)
        law = partial(ARRAY_LAWS[kind], m=m)
        sums = {"rate": lambda a, fx, fq, n: n / h, "law": lambda a, fx, fq, n: law(a, fx, fq), "z": lambda a, fx, fq, n: (n / h - (p := law(a, fx, fq))) / np.sqrt(p * (1 - p) / h)}
        total = tiles.pair_sums(tiles.coded(train, "data", s), tiles.coded(queries, "query", s), 1, sums).agg(*[F.sum(c).alias(c) for c in ("n_pairs", *sums)])
        n = F.nullif(F.col("n_pairs"), F.lit(0))
        return total.select(F.coalesce("n_pairs", F.lit(0).cast("bigint")).alias("n_pairs"), F.round(F.col("rate") / n, 6).alias("measured"), F.round(F.col("law") / n, 6).alias("law"), F.round(F.col("z") / n, 4).alias("mean_z"))

    law = {"minhash": "a / (fx + fq - a)", "opm1": "a / (m + fq - a)", "opm2": "a / (2 * m - a)", "srp": "1 - acos(a / sqrt(fx * fq)) / pi()", "normsign": "1 - acos(a / m) / pi()"}[kind]
    add(f"law_check_{kind}", run, O.query([*EMB, O.OV, *O.coded(kind, PARAMS.get(kind, {}), h, SEED), f"mc AS ({O.matches(h)})", f"p AS (SELECT matches / {h} AS r, {law} AS l FROM ov JOIN mc USING (q_id, x_id), mm)"], f"SELECT CAST(count(*) AS BIGINT) AS n_pairs, round(avg(r), 6) AS measured, round(avg(l), 6) AS law, round(avg((r - l) / sqrt(l * (1 - l) / {h})), 4) AS mean_z FROM p"))


for _kind in ("minhash", "opm1", "opm2", "srp", "normsign"):
    _law(_kind)

# ranking


RANK_COLLS = ("emb_bin", "turn_w", "docs_w")
RANK_KINDS = ("minhash", "opm1", "opm2", "l2alsh", "signalsh")


def ranked(spark: SparkSession, d: str, coll: str, kind: str, ks: tuple[int, ...]) -> tuple[DataFrame, DataFrame]:
    """(ranked list, gold of 100) of a collection's own split."""
    train, queries, m = halves(spark, d, coll)
    s = scheme(kind, max(ks), m)
    counts = ranking.match_counts(s.data_signatures(train), s.query_signatures(queries), ks)
    return ranking.rank_by_matches(counts), exact.exact_topk(train, queries, 100, "overlap")


def sides(spark: SparkSession, d: str, coll: str, kind: str, h: int, every: int = 0) -> tuple[DataFrame, DataFrame]:
    """Both sides of a collection's split with their codes, for tiles."""
    train, queries, m = halves(spark, d, coll)
    s = scheme(kind, h, m)
    return tiles.coded(train, "data", s, every=every), tiles.coded(queries, "query", s)


def gold_places(spark: SparkSession, d: str, kind: str) -> tuple[DataFrame, int]:
    """(places of the gold of 100 in the lists of turn_w, numbered and counted per query; number of data sets)."""
    x, q = (kept(side, "codes") for side in sides(spark, d, "turn_w", kind, N_RANK))
    n = x.count()
    gold = kept(tiles.top(x, q, 100), "gold")
    w = Window.partitionBy("q_id")
    seen = tiles.places(kept(tiles.stretches(x, n), "stretches"), q, gold, N_RANK, tiles.shares(q))
    return seen.select("q_id", "p", F.row_number().over(w.orderBy("p")).cast("bigint").alias("relevant_seen"), F.count("*").over(w).alias("g")), n


def _rounded(part: Column, whole: Column) -> Column:
    """The quotient of two counts to six places, halves up, in whole numbers."""
    return F.call_function("div", part * 2_000_000 + whole, whole * 2) / 1e6


#: Places of a list that are written one after another.
PIECE = 512


def pr_curve(spark: SparkSession, d: str, kind: str) -> DataFrame:
    """Every place of every list: between two gold places only the place changes.

    A task writes its lists side by side, ``PIECE`` places of each at a time: a file then
    repeats the same places, and further down nearly the same precisions, which take a
    small part of the disk that whole lists one after another take.
    """
    seen, n = gold_places(spark, d, kind)
    last = F.coalesce(F.lead("p").over(Window.partitionBy("q_id").orderBy("p")), F.lit(n + 1)) - 1
    run = lambda seen, first, last: F.struct(seen.alias("relevant_seen"), F.round(seen / F.col("g"), 6).alias("recall"), first.alias("first"), last.alias("last"))
    own, head = run(F.col("relevant_seen"), F.col("p"), F.col("last")), run(F.lit(0).cast("bigint"), F.lit(1).cast("bigint"), F.col("p") - 1)
    runs = seen.withColumn("last", last).select("q_id", F.explode(F.when(F.expr("relevant_seen = 1 and p > 1"), F.array(head, own)).otherwise(F.array(own))).alias("r"))
    pieces = runs.select("q_id", "r.*", F.explode(F.expr(f"sequence((r.first - 1) div {PIECE}, (r.last - 1) div {PIECE})")).alias("piece")).sortWithinPartitions(F.desc("piece"), "q_id", "first")
    start = F.col("piece") * PIECE
    walk = pieces.select("q_id", "relevant_seen", "recall", F.explode(F.sequence(F.greatest(F.col("first"), start + 1), F.least(F.col("last"), start + PIECE))).alias("p"))
    return walk.select("q_id", "p", "relevant_seen", _rounded(F.col("relevant_seen"), F.col("p")).alias("precision_"), "recall")


def _ranked_sql(coll: str, kind: str, k: int = N_RANK, h: int | None = None) -> list[str]:
    return [*O.split(coll), O.OV, O.gold(100), *O.coded(kind, PARAMS.get(kind, {}), h or k, SEED), O.ranked(k), O.WALK]


for _kind in KINDS:
    add(f"match_counts_{_kind}", lambda s, d, kind=_kind: ranked(s, d, "turn_w", kind, (N_RANK,))[0].select("q_id", "x_id", "matches"), O.query(_ranked_sql("turn_w", _kind), "SELECT q_id, x_id, CAST(matches AS BIGINT) AS matches FROM ranked"))
    add(f"ranked_{_kind}", lambda s, d, kind=_kind: tiles.top(*sides(s, d, "turn_w", kind, N_RANK), 20, N_RANK).select("q_id", F.col("rank").alias("p"), "x_id", F.col("score").alias("matches")), O.query(_ranked_sql("turn_w", _kind), "SELECT q_id, CAST(p AS BIGINT) AS p, x_id, CAST(matches AS BIGINT) AS matches FROM ranked WHERE p <= 20"))
    add(f"pr_curve_{_kind}", lambda s, d, kind=_kind: pr_curve(s, d, kind), O.query(_ranked_sql("turn_w", _kind), "SELECT q_id, CAST(p AS BIGINT) AS p, relevant_seen, round(relevant_seen / p, 6) AS precision_, round(relevant_seen / g, 6) AS recall FROM walk"))


@query(O.query(_ranked_sql("turn_w", "opm1"), "SELECT CAST(p AS BIGINT) AS p, round(avg(relevant_seen / p), 6) AS precision_, round(avg(relevant_seen / g), 6) AS recall FROM walk GROUP BY p"))
def mean_pr(spark: SparkSession, d: str) -> DataFrame:
    return ranking.mean_pr(ranking.pr_points(*ranked(spark, d, "turn_w", "opm1", (N_RANK,)))).select("p", "precision_", "recall")


@query(O.query([*_ranked_sql("turn_w", "opm1"), "lv AS (SELECT unnest(range(1, 11)) AS level)", "b AS (SELECT q_id, level, max(relevant_seen / p) AS pr FROM walk, lv WHERE is_gold = 1 AND relevant_seen / g >= level / 10.0::DOUBLE - 1e-12 GROUP BY q_id, level)"], "SELECT CAST(level AS INT) AS level, round(avg(pr), 6) AS precision_ FROM b GROUP BY level"))
def interpolated_pr(spark: SparkSession, d: str) -> DataFrame:
    points = gold_places(spark, d, "opm1")[0].select("q_id", F.lit(N_RANK).alias("k"), "p", F.lit(1).alias("is_gold"), "relevant_seen", "g")
    return ranking.interpolated(points).select("level", "precision_")


def _ap(spark: SparkSession, d: str, colls, kinds, ks) -> DataFrame:
    out = None
    for coll in colls:
        for kind in kinds:
            ap = ranking.average_precision(ranking.pr_points(*ranked(spark, d, coll, kind, ks)))
            one = ap.select(F.lit(coll).alias("collection"), F.lit(kind).alias("scheme"), "k", "n_queries", "ap")
            out = one if out is None else out.unionByName(one)
    return out


def _ap_sql(colls, kinds, ks) -> str:
    parts = [f"SELECT '{c}' AS collection, '{kind}' AS scheme, CAST({k} AS INT) AS k, * FROM ({O.query(_ranked_sql(c, kind, k, max(ks)), O.AP)})" for c in colls for kind in kinds for k in ks]
    return " UNION ALL ".join(parts)


add("ap_by_scheme", lambda s, d: _ap(s, d, ("turn_w",), RANK_KINDS, (N_RANK,)), _ap_sql(("turn_w",), RANK_KINDS, (N_RANK,)))
add("ranking_sweep", lambda s, d: _ap(s, d, RANK_COLLS, ("minhash", "opm1", "l2alsh", "signalsh"), (32, 64, 128)), _ap_sql(RANK_COLLS, ("minhash", "opm1", "l2alsh", "signalsh"), (32, 64, 128)))
add("padding_ablation", lambda s, d: _ap(s, d, ("turn_w", "cust_parts"), ("minhash", "opm1", "opm2"), (N_RANK,)), _ap_sql(("turn_w", "cust_parts"), ("minhash", "opm1", "opm2"), (N_RANK,)))
add("size_variation_effect", lambda s, d: _ap(s, d, ("part_supps", "user_hours", "conv_w", "turn_w"), ("minhash", "opm1"), (N_RANK,)), _ap_sql(("part_supps", "user_hours", "conv_w", "turn_w"), ("minhash", "opm1"), (N_RANK,)))


#: The four collections of the experiments, in the order of the source's four.
FOUR = ("docs_s3", "emb_bin", "docs_w", "conv_w")
RIVALS = ("minhash", "opm1", "l2alsh", "signalsh")
CURVE_KS = (32, 64, 128)


def _curves(spark: SparkSession, d: str) -> DataFrame:
    """Mean interpolated precision at ten recall levels, per collection, scheme and K.

    A ranking by matches has at most K + 1 tie groups a query; their sizes and gold
    give the curve at the groups' ends, so no list is sorted and no pair leaves its task.
    """
    out = None
    for coll in FOUR:
        train, queries, m = halves(spark, d, coll)
        gold = exact.exact_topk(train, queries, 100, "overlap")
        for kind in RIVALS:
            s = scheme(kind, max(CURVE_KS), m)
            groups = ranking.tie_groups(s.data_signatures(train), s.query_signatures(queries), gold, CURVE_KS)
            one = ranking.tie_curve(groups).select(F.lit(coll).alias("collection"), F.lit(kind).alias("scheme"), "k", "level", "precision_")
            out = one if out is None else out.unionByName(one)
    return out


def _curve_sql(coll: str, kind: str) -> str:
    ks = "(SELECT unnest([32, 64, 128]) AS k)"
    ctes = [
        *O.split(coll), O.OV, O.gold(100), *O.coded(kind, PARAMS.get(kind, {}), max(CURVE_KS), SEED),
        f"hit AS MATERIALIZED (SELECT q.id AS q_id, x.id AS x_id, k, count(*) AS matches FROM qcode q JOIN xcode x ON q.t = x.t AND q.code = x.code JOIN {ks} ON q.t < k GROUP BY q.id, x.id, k)",
        f"full_ AS MATERIALIZED (SELECT g.q_id, k, coalesce(h.matches, 0) AS matches, count(*) AS n, count(o.x_id) AS g FROM (SELECT qs.id AS q_id, xs.id AS x_id, k FROM qsets qs SEMI JOIN gold ON gold.q_id = qs.id CROSS JOIN xsets xs CROSS JOIN {ks}) g LEFT JOIN hit h USING (q_id, x_id, k) LEFT JOIN gold o ON o.q_id = g.q_id AND o.x_id = g.x_id GROUP BY g.q_id, k, coalesce(h.matches, 0))",
        "walk AS (SELECT q_id, k, sum(n) OVER w AS p, sum(g) OVER w AS seen, sum(g) OVER (PARTITION BY q_id, k) AS total FROM full_ WINDOW w AS (PARTITION BY q_id, k ORDER BY matches DESC))",
        "b AS (SELECT q_id, k, level, max(seen / p) AS pr FROM walk, (SELECT unnest(range(1, 11)) AS level) WHERE seen / total >= level / 10.0::DOUBLE - 1e-12 GROUP BY q_id, k, level)",
    ]
    return f"SELECT '{coll}' AS collection, '{kind}' AS scheme, CAST(k AS INT) AS k, CAST(level AS INT) AS level, precision_ FROM ({O.query(ctes, 'SELECT k, level, round(avg(pr), 6) AS precision_ FROM b GROUP BY k, level')})"


add("pr_curves", _curves, " UNION ALL ".join(_curve_sql(c, kind) for c in FOUR for kind in RIVALS))


@query(O.query([*_ranked_sql("turn_w", "opm1"), "z AS (SELECT r.q_id, matches, coalesce(a, 0) AS a FROM ranked r LEFT JOIN ov USING (q_id, x_id))"], "SELECT q_id, round(corr(matches, a), 5) AS corr FROM z GROUP BY q_id"))
def monotonicity(spark: SparkSession, d: str) -> DataFrame:
    """How closely matches follow the overlap, per query."""
    train, queries, m = halves(spark, d, "turn_w")
    s = scheme("opm1", N_RANK, m)
    counts = ranking.match_counts(s.data_signatures(train), s.query_signatures(queries), (N_RANK,))
    both = counts.join(exact.overlaps(train, queries).select("q_id", "x_id", "a"), ["q_id", "x_id"], "left")
    return both.groupBy("q_id").agg(F.round(F.corr("matches", F.coalesce("a", F.lit(0))), 5).alias("corr"))


@query(O.query(_ranked_sql("turn_w", "opm1"), f"SELECT q_id, x_id, CAST(a AS BIGINT) AS a, round((matches / {N_RANK}) * (m + fq) / (1 + matches / {N_RANK}), 6) AS estimate FROM ranked JOIN ov USING (q_id, x_id), mm"))
def estimate_overlap(spark: SparkSession, d: str) -> DataFrame:
    train, queries, m = halves(spark, d, "turn_w")
    s = scheme("opm1", N_RANK, m)
    both = tiles.pairs(tiles.coded(train, "data", s), tiles.coded(queries, "query", s), 1)
    return both.select("q_id", "x_id", "a", F.round(ranking.estimate_overlap(F.col("m0"), N_RANK, F.col("fq"), m), 6).alias("estimate"))


# bucketing: benchmark passages against documents


def index(spark: SparkSession, d: str, kind: str, k: int = K, l: int = L) -> tuple[bucketing.LshIndex, DataFrame, DataFrame]:  # noqa: E741
    x, q = (kept(s.where("f > 0"), "passages") for s in passages(spark, d))
    m = sets.padding_bound(x, "data_and_query", q)
    return bucketing.LshIndex.build(x, scheme(kind, k * l, m), k, l), x, q


def _bucket_sql(kind: str, k: int = K, l: int = L) -> list[str]:  # noqa: E741
    live = kind in ("opm1", "opm2")
    return [*PASSAGE, *O.coded(kind, PARAMS.get(kind, {}), k * l, SEED), f"xb AS MATERIALIZED ({O.buckets(k, l, 'xcode', live)})", f"qb AS MATERIALIZED ({O.buckets(k, l, 'qcode', live)})", "cand AS MATERIALIZED (SELECT DISTINCT q.id AS q_id, x.id AS x_id FROM qb q JOIN xb x USING (j, key))"]


@query(O.query(_bucket_sql("opm1"), "SELECT CAST(j AS INT) AS j, key, id FROM xb"))
def index_rows(spark: SparkSession, d: str) -> DataFrame:
    return index(spark, d, "opm1")[0].rows


@query(O.query(_bucket_sql("minhash"), "SELECT CAST(j AS INT) AS j, key, id FROM qb"))
def meta_hash(spark: SparkSession, d: str) -> DataFrame:
    ix, _, q = index(spark, d, "minhash")
    return ix.probes(q).select("j", "key", F.col("q_id").alias("id"))


for _kind in ("minhash", "opm1", "opm2", "l2alsh", "signalsh"):
    _k, _l = (8, 6) if _kind in ("l2alsh", "signalsh") else (1, 24)

    def _cands(spark, d, kind=_kind, k=_k, l=_l):  # noqa: E741
        ix, _, q = index(spark, d, kind, k, l)
        return ix.candidates(q)

    def _search(spark, d, kind=_kind, k=_k, l=_l):  # noqa: E741
        ix, x, q = index(spark, d, kind, k, l)
        return ix.search(x, q, 5)

    add(f"candidates_{_kind}", _cands, O.query(_bucket_sql(_kind, _k, _l), "SELECT q_id, x_id FROM cand"))
    add(f"search_{_kind}", _search, O.query([*_bucket_sql(_kind, _k, _l), "got AS (SELECT ov.* FROM ov SEMI JOIN cand USING (q_id, x_id))"], O.top("got", "a / fq", 5)))


@query(O.query([*_bucket_sql("opm1", 1, 48)], "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, CAST(fq AS BIGINT) AS fq, CAST(fx AS BIGINT) AS fx FROM ov SEMI JOIN cand USING (q_id, x_id) WHERE a >= ceil(0.9 * fq)"))
def containment_join(spark: SparkSession, d: str) -> DataFrame:
    ix, x, q = index(spark, d, "opm1", 1, 48)
    return ix.join(x, q, 0.9)


@query(O.query([*_bucket_sql("opm1", 1, 24), O.gold(10)], "SELECT g.q_id, CAST(coalesce(r.n, 0) AS BIGINT) AS reported, CAST(coalesce(h.n, 0) AS BIGINT) AS hits, CAST(g.n AS BIGINT) AS g FROM (SELECT q_id, count(*) AS n FROM gold GROUP BY q_id) g LEFT JOIN (SELECT q_id, count(*) AS n FROM cand GROUP BY q_id) r USING (q_id) LEFT JOIN (SELECT q_id, count(*) AS n FROM gold SEMI JOIN cand USING (q_id, x_id) GROUP BY q_id) h USING (q_id)"))
def bucket_eval(spark: SparkSession, d: str) -> DataFrame:
    ix, x, q = index(spark, d, "opm1", 1, 24)
    return bucketing.bucket_eval(ix.candidates(q), exact.exact_topk(x, q, 10, "overlap"), q)


@query(O.query(_bucket_sql("minhash"), "SELECT CAST(size AS BIGINT) AS size, CAST(count(*) AS BIGINT) AS n_buckets FROM (SELECT count(*) AS size FROM xb GROUP BY j, key) GROUP BY size"))
def bucket_histogram(spark: SparkSession, d: str) -> DataFrame:
    return index(spark, d, "minhash")[0].stats()


KMAX, LMAX, TS = 8, 32, (5, 10, 20, 50)
LEVELS = (0.1, 0.2, 0.3, 0.5, 0.7, 0.9)


def grid_cells(spark: SparkSession, d: str, coll: str, kind: str, kmax: int = KMAX, lmax: int = LMAX) -> tuple[DataFrame, DataFrame, int]:
    """(pairs by K and first table, gold of 50, number of pairs)."""
    x, q = sides(spark, d, coll, kind, kmax * lmax, kmax)
    gold = kept(tiles.top(x, q, 50), "gold")
    return kept(tiles.first_tables(x, q, gold, kmax, lmax, TS), "cells"), gold, x.count() * q.count()


def _grid_sql(coll: str, kind: str) -> list[str]:
    """Every (K, L) bucketed on its own."""
    live = "AND NOT bool_or(from_pad)" if kind in ("opm1", "opm2") else ""
    keys = lambda c: f"SELECT id, j, k, string_agg(CAST(code AS VARCHAR), '-' ORDER BY t) AS key FROM (SELECT *, t // {KMAX} AS j, t % {KMAX} AS place FROM {c}) JOIN (SELECT unnest(range(1, {KMAX + 1})) AS k) ON place < k GROUP BY id, j, k HAVING true {live}"
    return [
        *O.split(coll), O.OV, O.gold(50), *O.coded(kind, PARAMS.get(kind, {}), KMAX * LMAX, SEED), f"xk AS MATERIALIZED ({keys('xcode')})", f"qk AS MATERIALIZED ({keys('qcode')})",
        "met AS MATERIALIZED (SELECT DISTINCT q.id AS q_id, x.id AS x_id, k, j FROM qk q JOIN xk x USING (j, k, key))",
        f"spots AS (SELECT k, l FROM (SELECT unnest(range(1, {KMAX + 1})) AS k), (SELECT unnest(range(1, {LMAX + 1})) AS l))",
        "early AS MATERIALIZED (SELECT q_id, x_id, k, min(j) AS j FROM met GROUP BY q_id, x_id, k)",
        "rep AS MATERIALIZED (SELECT c.k, c.l, q_id, x_id FROM spots c JOIN early m ON m.k = c.k AND m.j < c.l)",
        f"grid AS MATERIALIZED (SELECT c.k, c.l, tt.t, coalesce(h.n, 0) AS hits, coalesce(r.n, 0) AS reported FROM spots c CROSS JOIN (SELECT unnest({list(TS)}) AS t) tt LEFT JOIN (SELECT k, l, count(*) AS n FROM rep GROUP BY k, l) r USING (k, l) LEFT JOIN (SELECT k, l, t, count(*) AS n FROM rep JOIN gold USING (q_id, x_id) JOIN (SELECT unnest({list(TS)}) AS t) ON rank <= t GROUP BY k, l, t) h ON h.k = c.k AND h.l = c.l AND h.t = tt.t)",
    ]


@query(O.query(_grid_sql("turn_w", "opm1"), "SELECT CAST(k AS INT) AS k, CAST(l AS INT) AS l, CAST(t AS INT) AS t, CAST(hits AS BIGINT) AS hits, CAST(reported AS BIGINT) AS reported FROM grid"))
def kl_grid(spark: SparkSession, d: str) -> DataFrame:
    return bucketing.grid_sums(grid_cells(spark, d, "turn_w", "opm1")[0], KMAX, LMAX, TS)


def _best_sql(coll: str, kind: str) -> str:
    return O.query([*_grid_sql(coll, kind), "tot AS (SELECT t, count(*) AS n FROM gold JOIN (SELECT unnest([5, 10, 20, 50]) AS t) ON rank <= t GROUP BY t)", "np AS (SELECT (SELECT count(*) FROM xsets) * (SELECT count(*) FROM qsets) AS n)"], f"SELECT CAST(t AS INT) AS t, level, CAST(b.k AS INT) AS k, CAST(b.l AS INT) AS l, round(b.reported / n, 6) AS fraction FROM (SELECT t, level, min({{'reported': reported, 'kl': k * l, 'k': k, 'l': l}}) AS b FROM grid JOIN tot USING (t), (SELECT unnest({list(LEVELS)}::DOUBLE[]) AS level) WHERE hits / tot.n >= level - 1e-12 GROUP BY t, level), np")


def _best(spark: SparkSession, d: str, coll: str, kind: str) -> DataFrame:
    cells, gold, pairs = grid_cells(spark, d, coll, kind)
    return bucketing.best_per_recall(bucketing.grid_sums(cells, KMAX, LMAX, TS), gold, pairs, LEVELS)


add("best_kl", lambda s, d: _best(s, d, "turn_w", "opm1"), _best_sql("turn_w", "opm1"))


def _sweep(spark: SparkSession, d: str, kmax: int = KMAX, lmax: int = LMAX) -> DataFrame:
    """The cheapest (K, L) at each recall level, for every T, scheme and collection of the experiment."""
    out = None
    for coll in FOUR:
        train, queries, m = halves(spark, d, coll)
        gold = kept(exact.exact_topk(train, queries, 50, "overlap"), "gold")
        n = train.count() * queries.count()
        for kind in RIVALS:
            s = scheme(kind, kmax * lmax, m)
            first = bucketing.prefix_tables(s.data_signatures(train), s.query_signatures(queries), kmax, lmax)
            best = bucketing.best_per_recall(kept(bucketing.grid_eval(first, gold, kmax, lmax, TS), "grid"), gold, n, LEVELS)
            one = best.select(F.lit(coll).alias("collection"), F.lit(kind).alias("scheme"), "t", "level", "k", "l", "fraction")
            out = one if out is None else out.unionByName(one)
    return out


add("bucketing_sweep", _sweep, " UNION ALL ".join(f"SELECT '{c}' AS collection, '{k}' AS scheme, * FROM ({_best_sql(c, k)})" for c in FOUR for k in RIVALS))


@query(O.query([*_bucket_sql("opm1")], "SELECT CAST(j AS INT) AS j, key, id FROM xb WHERE id % 7 <> 3"))
def index_incremental(spark: SparkSession, d: str) -> DataFrame:
    """Half the documents indexed, the rest added (some of them twice), one in seven deleted."""
    x, q = (s.where("f > 0") for s in passages(spark, d))
    s = scheme("opm1", K * L, sets.padding_bound(x, "data_and_query", q))
    ix = bucketing.LshIndex.build(x.where("id % 2 = 0"), s, K, L)
    return ix.upsert(x.where("id % 2 = 1 or id % 6 = 0")).delete(x.where("id % 7 = 3")).rows


# further workloads


@query(O.query([*EMB, O.OV], "SELECT 'emb_bin' AS collection, 64::BIGINT AS d, round(avg(a) / 64, 6) AS informative FROM ov"))
def sampling_informative(spark: SparkSession, d: str) -> DataFrame:
    """Mean chance that a sampled coordinate is in both sets."""
    train, queries, _ = halves(spark, d, "emb_bin")
    return exact.overlaps(train, queries).agg(F.round(F.avg("a") / 64, 6).alias("informative")).select(F.lit("emb_bin").alias("collection"), F.lit(64).cast("bigint").alias("d"), "informative")


_NAMES = O._words("part", "p_partkey", "p_name")


@query(f"WITH n AS MATERIALIZED (SELECT DISTINCT id, e FROM ({_NAMES})), k AS (SELECT id, string_agg(CAST(e AS VARCHAR), '-' ORDER BY e) AS key FROM n GROUP BY id) SELECT key, CAST(count(*) AS BIGINT) AS n, min(id) AS first_id FROM k GROUP BY key")
def record_match(spark: SparkSession, d: str) -> DataFrame:
    """Parts whose names hold the same words: records of one name, whatever its order."""
    s = sets.word_sets(load(spark, d, "part"), "p_partkey", "p_name")
    return s.groupBy(F.array_join(F.transform("elems", lambda e: e.cast("string")), "-").alias("key")).agg(F.count("*").alias("n"), F.min("id").alias("first_id"))


@query(O.query([*_bucket_sql("opm1", 1, 48)], "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, coalesce(quality, -1) AS quality FROM ov SEMI JOIN cand USING (q_id, x_id) LEFT JOIN labels ON doc_id = x_id WHERE a >= ceil(0.9 * fq)"))
def passage_containment(spark: SparkSession, d: str) -> DataFrame:
    labels = load(spark, d, "labels").select(F.col("doc_id").alias("x_id"), "quality")
    return containment_join(spark, d).join(labels, "x_id", "left").select("q_id", "x_id", "a", F.coalesce("quality", F.lit(-1)).alias("quality"))


@query(O.query(PASSAGE, "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, CAST(fq AS BIGINT) AS fq, CAST(fx AS BIGINT) AS fx FROM ov WHERE a >= ceil(0.9 * fq)"))
def containment_join_whole(spark: SparkSession, d: str) -> DataFrame:
    """Every pair of containment 0.9, by the prefix filter; ``containment_join`` gives those its index meets."""
    x, q = (kept(s.where("f > 0"), "passages") for s in passages(spark, d))
    found = exact.InvertedIndex(x).search_threshold(x, q, 0.9)
    sized = found.join(q.select(F.col("id").alias("q_id"), F.col("f").cast("bigint").alias("fq")), "q_id")
    return sized.join(x.select(F.col("id").alias("x_id"), F.col("f").cast("bigint").alias("fx")), "x_id").select("q_id", "x_id", "a", "fq", "fx")


@query(O.query(PASSAGE, "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, coalesce(quality, -1) AS quality FROM ov LEFT JOIN labels ON doc_id = x_id WHERE a >= ceil(0.9 * fq)"))
def passage_containment_whole(spark: SparkSession, d: str) -> DataFrame:
    labels = load(spark, d, "labels").select(F.col("doc_id").alias("x_id"), "quality")
    return containment_join_whole(spark, d).join(labels, "x_id", "left").select("q_id", "x_id", "a", F.coalesce("quality", F.lit(-1)).alias("quality"))


@query(O.query([*O.base("docs_w"), O.draws(48, SEED), "keyed AS MATERIALIZED (SELECT id, string_agg(CAST(e AS VARCHAR), '-' ORDER BY e) AS k FROM inc GROUP BY id)", "cls AS MATERIALIZED (SELECT min(id) AS id, count(*) AS copies FROM keyed GROUP BY k)", f"code AS MATERIALIZED (SELECT * FROM ({O.raw('inc')}) SEMI JOIN cls USING (id))", "b AS MATERIALIZED (SELECT id, t // 4 AS j, string_agg(CAST(code AS VARCHAR), '-' ORDER BY t) AS key FROM code GROUP BY id, t // 4)", "c AS (SELECT DISTINCT x.id AS id1, y.id AS id2 FROM b x JOIN b y ON x.j = y.j AND x.key = y.key AND x.id < y.id)", "o AS (SELECT id1, id2, count(*) AS a FROM c JOIN inc x ON x.id = id1 JOIN inc y ON y.id = id2 AND y.e = x.e GROUP BY id1, id2)"], "SELECT id1, id2, round(a / (s.f + t.f - a), 6) AS value, CAST(u.copies AS BIGINT) AS copies1, CAST(v.copies AS BIGINT) AS copies2 FROM o JOIN sets s ON s.id = id1 JOIN sets t ON t.id = id2 JOIN cls u ON u.id = id1 JOIN cls v ON v.id = id2 WHERE a / (s.f + t.f - a) >= 0.8 UNION ALL SELECT id, id, 1.0, CAST(copies AS BIGINT), CAST(copies AS BIGINT) FROM cls WHERE copies > 1"))
def near_duplicates(spark: SparkSession, d: str) -> DataFrame:
    """Classes of identical word sets, by their least id and how many they are: pairs of
    classes of resemblance 0.8 that share a bucket, and each class of several with itself."""
    x = kept(collection(spark, d, "docs_w").where("f > 0"), "docs_w")
    # classes go by a digest and tables by hashed keys, so elements travel only for pairs that are verified
    digest = F.sha2(F.array_join(F.transform("elems", lambda e: e.cast("string")), "-"), 256)
    keys = F.transform(F.sequence(F.lit(0), F.lit(11)), lambda j: F.xxhash64(F.slice("s0", j * 4 + 1, F.lit(4))))
    rows = tiles.coded(x, "data", schemes.minhash(48, SEED)).select("id", F.size("elems").alias("f"), keys.alias("keys"), digest.alias("digest"))
    classes = kept(rows.groupBy("digest").agg(F.min(F.struct("id", "f", "keys")).alias("r"), F.count("*").alias("copies")).select("r.id", "r.f", "r.keys", "copies"), "classes")
    table = classes.select("id", "f", F.posexplode("keys").alias("j", "key"))
    met = planner.salted_join(table.toDF("q_id", "f1", "j", "key"), table.toDF("x_id", "f2", "j", "key"), ["j", "key"], 50_000)
    # no pair of resemblance 0.8 differs more in size
    pairs = kept(met.where((F.col("q_id") < F.col("x_id")) & (F.least("f1", "f2") >= F.lit(0.8) * F.greatest("f1", "f2") - 1e-9)).select("q_id", "x_id").distinct(), "pairs")
    paired = pairs.select(F.col("q_id").alias("id")).unionByName(pairs.select(F.col("x_id").alias("id"))).distinct()
    some = x.join(planner.broadcast_if_small(paired), "id", "left_semi")
    found = bucketing.verify(pairs, some, some)
    r = M.resemblance(F.col("a"), F.col("fx"), F.col("fq"))
    near = found.where(r >= 0.8).select(F.col("q_id").alias("id1"), F.col("x_id").alias("id2"), F.round(r, 6).alias("value"))
    one, two = classes.select(F.col("id").alias("id1"), F.col("copies").alias("copies1")), classes.select(F.col("id").alias("id2"), F.col("copies").alias("copies2"))
    same = classes.where("copies > 1").select(F.col("id").alias("id1"), F.col("id").alias("id2"), F.lit(1.0).alias("value"), F.col("copies").alias("copies1"), F.col("copies").alias("copies2"))
    return near.join(one, "id1").join(two, "id2").select("id1", "id2", "value", "copies1", "copies2").unionByName(same)


@query(O.query([*O.split("cust_parts"), O.OV, f"g AS ({O.top('ov', 'a', 3)})"], f"SELECT q_id, e, CAST(count(*) AS BIGINT) AS votes FROM g JOIN xinc ON id = x_id ANTI JOIN qinc ON qinc.id = q_id AND qinc.e = xinc.e GROUP BY q_id, e HAVING count(*) >= 2"))
def basket_neighbors(spark: SparkSession, d: str) -> DataFrame:
    """Parts that two of a customer's three nearest baskets hold and the customer's does not."""
    train, queries, _ = halves(spark, d, "cust_parts")
    near = exact.exact_topk(train, queries, 3, "overlap").select("q_id", "x_id")
    wares = near.join(sets.incidence(train).withColumnRenamed("id", "x_id"), "x_id")
    own = sets.incidence(queries).withColumnRenamed("id", "q_id")
    return wares.join(own, ["q_id", "e"], "left_anti").groupBy("q_id", "e").agg(F.count("*").alias("votes")).where("votes >= 2")


@query()
def faster_sampling(spark: SparkSession, d: str) -> DataFrame:
    """Match rates of two-sided padding and of its weighted form, over all overlapping pairs."""
    train, queries, m = halves(spark, d, "emb_bin")
    h = 64
    made = schemes.opm2(h, SEED, m), schemes.opmw(h, SEED, m)
    sums = {"padded": lambda a, fx, fq, n, fast: n / h, "weighted": lambda a, fx, fq, n, fast: fast / h, "law": lambda a, fx, fq, n, fast: a / (2 * m - a)}
    total = tiles.pair_sums(tiles.coded(train, "data", *made), tiles.coded(queries, "query", *made), 2, sums).agg(*[F.sum(c).alias(c) for c in ("n_pairs", *sums)])
    n = F.nullif(F.col("n_pairs"), F.lit(0))
    return total.select(F.coalesce("n_pairs", F.lit(0).cast("bigint")).alias("n_pairs"), *[F.round(F.col(c) / n, 4).alias(c) for c in sums])


def _policy(spark: SparkSession, d: str) -> DataFrame:
    train, queries, m = halves(spark, d, "turn_w")
    gold = exact.exact_topk(train, queries, 100, "overlap")
    raw = schemes.minhash(N_RANK, SEED)
    xs, qs = raw.data_signatures(train), raw.query_signatures(queries)
    out = None
    for policy, q in (("max", None), ("q99", 0.99), ("q95", 0.95), ("q50", 0.5)):
        bound = m if q is None else sets.padding_bound(train, "quantile", quantile=q)
        counts = ranking.match_counts(schemes.repad(xs, schemes.opm1(N_RANK, SEED, bound)), qs, (N_RANK,))
        ap = ranking.average_precision(ranking.pr_points(ranking.rank_by_matches(counts), gold))
        one = ap.select(F.lit(policy).alias("policy"), F.lit(bound).cast("bigint").alias("m"), "n_queries", "ap")
        out = one if out is None else out.unionByName(one)
    return out


def _policy_sql() -> str:
    parts = []
    for policy, m in (("max", "max(f)"), ("q99", "floor(quantile_cont(f, 0.99))"), ("q95", "floor(quantile_cont(f, 0.95))"), ("q50", "floor(quantile_cont(f, 0.5))")):
        source = "sets" if policy == "max" else "xsets"
        ctes = [c if not c.startswith("mm AS") else f"mm AS MATERIALIZED (SELECT CAST({m} AS BIGINT) AS m FROM {source})" for c in _ranked_sql("turn_w", "opm1")]
        parts.append(f"SELECT '{policy}' AS policy, m, n_queries, ap FROM ({O.query(ctes, 'SELECT * FROM (' + O.AP + '), mm')})")
    return " UNION ALL ".join(parts)


add("m_policy_sweep", _policy, _policy_sql())
