"""Registered queries: relational operators around the methods, functions, formats and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from overlapix.functions import hashing as H
from overlapix.functions import measures as M
from overlapix.functions import udfs
from overlapix.operators import bucketing, exact, schemes, sets
from overlapix.plans import oracle as O
from overlapix.plans import planner
from overlapix.plans.catalog_hash import SEED, _bucket_sql, index
from overlapix.plans.catalog_sets import PASSAGE, passages
from overlapix.plans.registry import query
from overlapix.sources import formats
from overlapix.sources.tables import collection, load
from overlapix.streaming import streams


@query("SELECT doc_id, lang, CAST(n_chars AS BIGINT) AS n_chars FROM documents WHERE n_chars >= 2000 AND lang IN ('en', 'de')")
def scan_documents_filtered(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").where((F.col("n_chars") >= 2000) & F.col("lang").isin("en", "de")).select("doc_id", "lang", "n_chars")


@query(O.query(O.base("emb_bin"), "SELECT kind, id, CAST(count(*) AS BIGINT) AS f, CAST(sum(e) AS BIGINT) AS fp_sum, min(e) AS fp_min FROM inc, (SELECT unnest(['parquet', 'orc', 'json', 'csv']) AS kind) GROUP BY kind, id"))
def roundtrip_formats(spark: SparkSession, d: str) -> DataFrame:
    s, out = collection(spark, d, "emb_bin"), None
    for kind in formats.FORMATS:
        path = formats.scratch(spark, kind)
        formats.save(s, path, kind)
        one = sets.set_profile(formats.read(spark, path, formats.SCHEMAS["set"], kind)).select(F.lit(kind).alias("kind"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query(O.query([O.draws(4, SEED), "mm AS (SELECT 500 AS m)", O.pads(H.PAD_A, "padA")], "SELECT CAST(t AS INT) AS t, CAST(min(n) AS BIGINT) AS m_from, low AS pad_min FROM padA GROUP BY t, low"))
def source_staircase(spark: SparkSession, d: str) -> DataFrame:
    spark.dataSource.register(formats.StaircaseSource)
    return spark.read.format("pad_staircase").option("h", 4).option("m", 500).option("seed", SEED).load()


@query(O.query(O.base("docs_w"), "SELECT id, CAST(f AS BIGINT) AS f FROM sets WHERE f BETWEEN 100 AND 400"))
def filter_size_band(spark: SparkSession, d: str) -> DataFrame:
    return collection(spark, d, "docs_w").where(F.col("f").between(100, 400)).select("id", F.col("f").cast("bigint").alias("f"))


@query(O.query(_bucket_sql("opm1"), "SELECT CAST(q.j AS INT) AS j, q.id AS q_id, x.id AS x_id FROM qb q JOIN xb x USING (j, key)"))
def join_broadcast_bucket(spark: SparkSession, d: str) -> DataFrame:
    ix, _, q = index(spark, d, "opm1")
    return ix.rows.select("j", "key", F.col("id").alias("x_id")).join(F.broadcast(ix.probes(q)), ["j", "key"]).select("j", "q_id", "x_id")


@query(O.query(_bucket_sql("opm1"), "SELECT q_id, x_id, CAST(coalesce(a, 0) AS BIGINT) AS a FROM cand LEFT JOIN ov USING (q_id, x_id)"))
def join_smj_verify(spark: SparkSession, d: str) -> DataFrame:
    ix, x, q = index(spark, d, "opm1")
    right = x.select(F.col("id").alias("x_id"), F.col("elems").alias("xe")).hint("merge")
    both = ix.candidates(q).join(right, "x_id").join(q.select(F.col("id").alias("q_id"), F.col("elems").alias("qe")).hint("merge"), "q_id")
    return both.select("q_id", "x_id", M.overlap(F.col("qe"), F.col("xe")).cast("bigint").alias("a"))


@query(O.query(O.split("emb_bin"), "SELECT q.id AS q_id, CAST(count(*) AS BIGINT) AS n FROM qsets q JOIN xsets x ON x.f >= ceil(0.9 * q.f) GROUP BY q.id"))
def join_theta_size(spark: SparkSession, d: str) -> DataFrame:
    """How many sets are large enough to contain nine tenths of each query."""
    train, queries = sets.split_partitions(collection(spark, d, "emb_bin"))
    q = planner.broadcast_if_small(queries.select(F.col("id").alias("q_id"), F.col("f").alias("fq")), required=True)
    x = train.select(F.col("f").alias("fx"))
    return x.join(q, planner.size_filter("fx", "fq", 0.9)).groupBy("q_id").agg(F.count("*").alias("n"))


@query(O.query(O.split("emb_bin"), "SELECT q.id AS q_id, x.id AS x_id FROM qsets q JOIN xsets x ON x.f BETWEEN q.f - 1 AND q.f + 1"))
def join_range_band(spark: SparkSession, d: str) -> DataFrame:
    """Sizes that differ by one at most: bands of width two, each size probing the bands its range meets."""
    train, queries = sets.split_partitions(collection(spark, d, "emb_bin"))
    q = queries.select(F.col("id").alias("q_id"), F.col("f").alias("fq"), F.explode(F.sequence(F.floor((F.col("f") - 1) / 2), F.floor((F.col("f") + 1) / 2))).alias("band"))
    x = train.select(F.col("id").alias("x_id"), F.col("f").alias("fx"), F.floor(F.col("f") / 2).alias("band"))
    return x.join(q, "band").where(F.abs(F.col("fx") - F.col("fq")) <= 1).select("q_id", "x_id")


@query("SELECT p.event_id AS p_id, c.event_id AS c_id FROM events p JOIN events c ON p.user_id = c.user_id AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR WHERE p.event_type = 'purchase' AND c.event_type = 'click'")
def join_interval_events(spark: SparkSession, d: str) -> DataFrame:
    """Time is cut into hours, so the join is on the user and the hour."""
    e = load(spark, d, "events")
    hour = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / 3600)
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("p_id"), "user_id", F.col("ts").alias("p_ts"), F.explode(F.array(hour("ts"), hour("ts") - 1)).alias("h"))
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("c_id"), "user_id", F.col("ts").alias("c_ts"), hour("ts").alias("h"))
    return p.join(c, ["user_id", "h"]).where("c_ts <= p_ts and c_ts >= p_ts - interval 1 hour").select("p_id", "c_id")


@query("SELECT p.event_id AS p_id, coalesce(c.event_id, -1) AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts")
def join_asof_events(spark: SparkSession, d: str) -> DataFrame:
    """Each purchase with the user's last click before it: one pass over a user's events in order."""
    e = load(spark, d, "events").where("event_type in ('purchase', 'click')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_click", last).where("event_type = 'purchase'").select(F.col("event_id").alias("p_id"), F.coalesce("last_click", F.lit(-1)).alias("last_click"))


@query(O.query(_bucket_sql("opm1"), "SELECT id FROM xsets SEMI JOIN (SELECT x_id AS id FROM cand) USING (id)"))
def semi_candidates(spark: SparkSession, d: str) -> DataFrame:
    ix, x, q = index(spark, d, "opm1")
    return x.join(ix.candidates(q).select(F.col("x_id").alias("id")), "id", "left_semi").select("id")


@query(O.query(_bucket_sql("opm1"), "SELECT id FROM xsets ANTI JOIN (SELECT x_id AS id FROM cand) USING (id)"))
def anti_candidates(spark: SparkSession, d: str) -> DataFrame:
    ix, x, q = index(spark, d, "opm1")
    return x.join(ix.candidates(q).select(F.col("x_id").alias("id")), "id", "left_anti").select("id")


@query(O.query(PASSAGE, "SELECT q_id, CAST(count(*) AS BIGINT) AS n, CAST(sum(a) AS BIGINT) AS total, CAST(max(a) AS BIGINT) AS best, arg_max(x_id, (a, -x_id)) AS best_id FROM ov GROUP BY q_id"))
def agg_overlap_counts(spark: SparkSession, d: str) -> DataFrame:
    return exact.overlaps(*passages(spark, d)).groupBy("q_id").agg(F.count("*").alias("n"), F.sum("a").alias("total"), F.max("a").alias("best"), F.max_by("x_id", F.struct("a", -F.col("x_id"))).alias("best_id"))


@query(f"SELECT lang, CAST(count(DISTINCT tok) AS BIGINT) AS n FROM (SELECT lang, unnest({O.WORDS.format('text')}) AS tok FROM documents) GROUP BY lang")
def agg_distinct_tokens(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").select("lang", F.explode(sets.tokens(F.col("text"))).alias("tok")).groupBy("lang").agg(F.countDistinct("tok").alias("n"))


_STATS = "CAST(count(*) AS BIGINT) AS n, CAST(sum(n_chars) AS BIGINT) AS chars"


def _doc_stats(grouped) -> DataFrame:
    return grouped.agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query(f"SELECT lang, source, {_STATS} FROM documents GROUP BY CUBE (lang, source)")
def cube_doc_stats(spark: SparkSession, d: str) -> DataFrame:
    return _doc_stats(load(spark, d, "documents").cube("lang", "source"))


@query(f"SELECT lang, source, {_STATS} FROM documents GROUP BY ROLLUP (lang, source)")
def rollup_doc_stats(spark: SparkSession, d: str) -> DataFrame:
    return _doc_stats(load(spark, d, "documents").rollup("lang", "source"))


@query(f"SELECT lang, source, {_STATS} FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def gsets_doc_stats(spark: SparkSession, d: str) -> DataFrame:
    return _doc_stats(load(spark, d, "documents").groupingSets([["lang"], ["source"], []], "lang", "source"))


@query("SELECT source, CAST(count(*) FILTER (lang = 'de') AS BIGINT) AS de, CAST(count(*) FILTER (lang = 'en') AS BIGINT) AS en, CAST(count(*) FILTER (lang = 'es') AS BIGINT) AS es, CAST(count(*) FILTER (lang = 'fr') AS BIGINT) AS fr FROM documents GROUP BY source")
def pivot_quality(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT source, lang, CAST(count(*) AS BIGINT) AS n FROM documents GROUP BY source, lang")
def unpivot_counts(spark: SparkSession, d: str) -> DataFrame:
    return pivot_quality(spark, d).unpivot("source", ["de", "en", "es", "fr"], "lang", "n").where("n > 0")


@query(O.query([*PASSAGE], f"SELECT q_id, x_id, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER v AS BIGINT) AS rk, CAST(dense_rank() OVER v AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS quarter, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM ov WINDOW v AS (PARTITION BY q_id ORDER BY a DESC), w AS (PARTITION BY q_id ORDER BY a DESC, {O.TIE})"))
def win_rank_overlap(spark: SparkSession, d: str) -> DataFrame:
    v = Window.partitionBy("q_id").orderBy(F.desc("a"))
    w = Window.partitionBy("q_id").orderBy(F.desc("a"), *exact.tie_order())
    big = lambda c: c.cast("bigint")
    return exact.overlaps(*passages(spark, d)).select("q_id", "x_id", big(F.row_number().over(w)).alias("rn"), big(F.rank().over(v)).alias("rk"), big(F.dense_rank().over(v)).alias("dr"), big(F.ntile(4).over(w)).alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@query("SELECT event_id, lag(event_id, 1, -1) OVER w AS before, lead(event_id, 1, -1) OVER w AS after, first_value(event_id) OVER w AS first_id, coalesce(nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_events(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 1, -1).over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.coalesce(F.nth_value("event_id", 2).over(whole), F.lit(-1)).alias("second_id"))


@query("SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS BIGINT) AS n5, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running FROM events")
def win_frame_running(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.count("*").over(w.rowsBetween(-4, 0)).alias("n5"), F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"))


@query("SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS BIGINT) AS day FROM events")
def win_range_value(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-86400, 0)
    return load(spark, d, "events").select("event_id", F.count("*").over(w).alias("day"))


@query(O.query(PASSAGE, f"SELECT q_id, x_id, CAST(a AS BIGINT) AS a FROM ov ORDER BY a DESC, q_id, {O.TIE} LIMIT 100"))
def topk_pairs(spark: SparkSession, d: str) -> DataFrame:
    return exact.overlaps(*passages(spark, d)).orderBy(F.desc("a"), "q_id", *exact.tie_order()).limit(100).select("q_id", "x_id", "a")


def _two(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    out = []
    for kind in ("minhash", "opm1"):
        ix, _, q = index(spark, d, kind)
        out.append(ix.candidates(q))
    return out[0], out[1]


def _two_sql(op: str) -> str:
    return f"SELECT * FROM ({O.query(_bucket_sql('minhash'), 'SELECT q_id, x_id FROM cand')}) {op} SELECT * FROM ({O.query(_bucket_sql('opm1'), 'SELECT q_id, x_id FROM cand')})"


@query(_two_sql("UNION"))
def setop_union(spark: SparkSession, d: str) -> DataFrame:
    a, b = _two(spark, d)
    return a.union(b).distinct()


@query(_two_sql("INTERSECT"))
def setop_intersect(spark: SparkSession, d: str) -> DataFrame:
    a, b = _two(spark, d)
    return a.intersect(b)


@query(_two_sql("EXCEPT ALL"))
def setop_except(spark: SparkSession, d: str) -> DataFrame:
    a, b = _two(spark, d)
    return a.exceptAll(b)


@query("SELECT doc_id, n_chars FROM documents o WHERE n_chars > (SELECT avg(n_chars) FROM documents i WHERE i.lang = o.lang) AND EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = o.doc_id)")
def subquery_above_avg(spark: SparkSession, d: str) -> DataFrame:
    load(spark, d, "documents").createOrReplaceTempView("overlapix_documents")
    load(spark, d, "labels").createOrReplaceTempView("overlapix_labels")
    return spark.sql("WITH o AS (SELECT doc_id, n_chars, lang FROM overlapix_documents) SELECT doc_id, n_chars FROM o WHERE n_chars > (SELECT avg(n_chars) FROM overlapix_documents i WHERE i.lang = o.lang) AND EXISTS (SELECT 1 FROM overlapix_labels l WHERE l.doc_id = o.doc_id)")


@query("SELECT p_partkey, lower(p_name) AS low, length(p_name) AS n, split_part(p_name, ' ', 1) AS head, regexp_replace(p_brand, '[0-9]+', '#') AS brand, translate(p_type, 'AEIOU', 'aeiou') AS vowels, levenshtein(split_part(p_name, ' ', 1), split_part(p_name, ' ', 2)) AS dist FROM part")
def fn_string(spark: SparkSession, d: str) -> DataFrame:
    word = lambda i: F.split_part("p_name", F.lit(" "), F.lit(i))
    return load(spark, d, "part").select("p_partkey", F.lower("p_name").alias("low"), F.length("p_name").cast("bigint").alias("n"), word(1).alias("head"), F.regexp_replace("p_brand", "[0-9]+", "#").alias("brand"), F.translate("p_type", "AEIOU", "aeiou").alias("vowels"), F.levenshtein(word(1), word(2)).cast("bigint").alias("dist"))


@query("SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(count(*) AS BIGINT) AS n, CAST(sum(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS BIGINT) AS days, CAST(count(*) FILTER (o_orderdate + INTERVAL 30 DAY >= date_trunc('month', o_orderdate) + INTERVAL 1 MONTH) AS BIGINT) AS over FROM orders GROUP BY ALL")
def fn_date(spark: SparkSession, d: str) -> DataFrame:
    o = F.col("o_orderdate")
    over = (o + F.expr("INTERVAL 30 DAY")) >= F.date_trunc("month", o) + F.expr("INTERVAL 1 MONTH")
    return load(spark, d, "orders").groupBy(F.year(o).cast("bigint").alias("y"), F.month(o).cast("bigint").alias("m")).agg(F.count("*").alias("n"), F.sum(F.datediff(o, F.lit("1992-01-01").cast("date"))).cast("bigint").alias("days"), F.count(F.when(over, 1)).alias("over"))


@query("SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_retailprice), 6) AS s, CAST(floor(p_retailprice / 7) AS BIGINT) AS f, CAST(p_partkey % 16 AS BIGINT) AS md, CAST(xor(p_partkey, 5) AS BIGINT) AS x, CAST(bit_count(p_partkey) AS BIGINT) AS bits FROM part")
def fn_math(spark: SparkSession, d: str) -> DataFrame:
    k, price = F.col("p_partkey"), F.col("p_retailprice")
    return load(spark, d, "part").select("p_partkey", F.round(F.log(price), 6).alias("l"), F.round(F.sqrt(price), 6).alias("s"), F.floor(price / 7).alias("f"), F.pmod(k, F.lit(16)).alias("md"), k.bitwiseXOR(F.lit(5)).alias("x"), F.bit_count(k).cast("bigint").alias("bits"))


@query("WITH v AS (SELECT vec_id, list_filter(range(64), lambda i: embedding[i + 1] > 0) AS on_, list_filter(range(64), lambda i: embedding[i + 1] > 0.1) AS hi FROM embeddings) SELECT vec_id, CAST(len(on_) AS BIGINT) AS n, CAST(len(hi) AS BIGINT) AS n_hi, CAST(len(list_intersect(on_, hi)) AS BIGINT) AS both, CAST(len(on_) - len(hi) AS BIGINT) AS gap, CAST(list_sum(list_transform(on_, lambda i: i * i)) AS BIGINT) AS squares, on_[1] AS first_on FROM v")
def fn_array(spark: SparkSession, d: str) -> DataFrame:
    above = lambda t: F.filter(F.transform("embedding", lambda v, i: F.when(v > F.lit(t), i.cast("bigint"))), lambda i: i.isNotNull())
    v = load(spark, d, "embeddings").select("vec_id", above(0.0).alias("on_"), above(0.1).alias("hi"))
    return v.select("vec_id", F.size("on_").cast("bigint").alias("n"), F.size("hi").cast("bigint").alias("n_hi"), F.size(F.array_intersect("on_", "hi")).cast("bigint").alias("both"), F.size(F.array_except("on_", "hi")).cast("bigint").alias("gap"), F.aggregate("on_", F.lit(0).cast("bigint"), lambda a, i: a + i * i).alias("squares"), F.get("on_", F.lit(0)).alias("first_on"))


@query("SELECT user_id, CAST(count(DISTINCT event_type) AS BIGINT) AS kinds, CAST(count(*) FILTER (event_type = 'click') AS BIGINT) AS clicks, CAST(count(*) AS BIGINT) AS total FROM events GROUP BY user_id")
def fn_map(spark: SparkSession, d: str) -> DataFrame:
    counts = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda a, v: a + v)
    return m.select("user_id", F.size(F.map_filter("m", lambda k, v: v > 0)).cast("bigint").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0).cast("bigint")).alias("clicks"), total.alias("total"))


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def fn_json(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").groupBy(F.from_json("props", "k bigint")["k"].alias("k")).agg(F.count("*").alias("n"))


@query(f"SELECT doc_id FROM documents WHERE {O.fp('CAST(doc_id AS VARCHAR)')} % 20 = 0")
def sample_hash(spark: SparkSession, d: str) -> DataFrame:
    """A sample that every engine and every run draws alike."""
    return load(spark, d, "documents").where(H.fp(F.col("doc_id").cast("string")) % 20 == 0).select("doc_id")


@query("SELECT date_trunc('day', ts) AS start, event_type, CAST(count(*) AS BIGINT) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def ev_tumbling(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


@query("SELECT start, CAST(count(*) AS BIGINT) AS n FROM (SELECT date_trunc('day', ts) + INTERVAL (h * 12) HOUR AS start, ts FROM events, (SELECT unnest([-1, 0, 1]) AS h)) WHERE ts >= start AND ts < start + INTERVAL 1 DAY GROUP BY start")
def ev_sliding(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


@query("WITH g AS (SELECT user_id, ts, sum(CASE WHEN last IS NULL OR ts >= last + INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS last FROM events)) SELECT user_id, min(ts) AS start, CAST(count(*) AS BIGINT) AS n FROM g GROUP BY user_id, s")
def ev_session(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


_HOURS = O.base("user_hours")


@query(O.query([*_HOURS, O.draws(8, SEED)], f"SELECT id, CAST(t AS INT) AS t, code FROM ({O.raw('inc')})"))
def udf_scalar(spark: SparkSession, d: str) -> DataFrame:
    s = collection(spark, d, "user_hours")
    return s.select("id", F.posexplode(udfs.minhash_codes(8, SEED)("elems")).alias("t", "code"))


@query(O.query([*_HOURS, O.draws(8, SEED)], f"SELECT id, CAST(t AS INT) AS t, code FROM ({O.raw('inc')})"))
def udaf_minhash(spark: SparkSession, d: str) -> DataFrame:
    inc = sets.incidence(collection(spark, d, "user_hours"))
    return inc.groupBy("id").agg(udfs.minhash_agg(8, SEED)("e").alias("sig")).select("id", F.posexplode("sig").alias("t", "code"))


@query(O.query([*_HOURS, O.draws(8, SEED)], f"SELECT id, CAST(t AS INT) AS t, code FROM ({O.raw('inc', 'affine')})"))
def udaf_minhash_native(spark: SparkSession, d: str) -> DataFrame:
    inc = sets.incidence(collection(spark, d, "user_hours"))
    made = inc.groupBy("id").agg(*udfs.minhash_columns("e", 8, SEED))
    return made.select("id", F.posexplode(F.array(*[f"c{t}" for t in range(8)])).alias("t", "code"))


@query(O.query([*_HOURS, O.draws(8, SEED), f"code AS ({O.raw('inc')})"], "SELECT id, CAST(t // 2 AS INT) AS j, string_agg(CAST(code AS VARCHAR), '-' ORDER BY t) AS key FROM code GROUP BY id, t // 2"))
def udtf_bands(spark: SparkSession, d: str) -> DataFrame:
    schemes.minhash(8, SEED).data_signatures(collection(spark, d, "user_hours")).createOrReplaceTempView("overlapix_sig")
    udfs.register(spark)
    return spark.sql("SELECT s.id, b.j, b.key FROM overlapix_sig s, LATERAL bands(s.sig, 2, 4) b")


@query(O.query(PASSAGE, "SELECT q_id, x_id, CAST(a AS BIGINT) AS a, round(a / fq, 6) AS c, round(a / (2000 + fq - a), 6) AS s FROM ov WHERE a / fq >= 0.5"))
def sql_surface(spark: SparkSession, d: str) -> DataFrame:
    udfs.register(spark)
    x, q = passages(spark, d)
    pairs = exact.overlaps(x, q).select("q_id", "x_id")
    e = pairs.join(x.select(F.col("id").alias("x_id"), F.col("elems").alias("xe")), "x_id").join(F.broadcast(q.select(F.col("id").alias("q_id"), F.col("elems").alias("qe"))), "q_id")
    return spark.sql("SELECT q_id, x_id, set_overlap(qe, xe) AS a, round(set_containment(qe, xe), 6) AS c, round(opm1_sim(set_overlap(qe, xe), size(qe), {m}), 6) AS s FROM {e} WHERE set_containment(qe, xe) >= 0.5", e=e, m=2000)


# streams, read to their end


def _days(spark: SparkSession, d: str) -> str:
    path = formats.scratch(spark, "days")
    streams.cut_into_days(spark, load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")), path)
    return path


@query()
def stream_watermark(spark: SparkSession, d: str) -> DataFrame:
    return streams.drain(streams.hourly_counts(streams.event_stream(spark, _days(spark, d), 1)), "counts")


@query()
def stream_signature(spark: SparkSession, d: str) -> DataFrame:
    sig = streams.signature_stream(streams.event_stream(spark, _days(spark, d)), 8, SEED)
    return streams.latest_signatures(streams.drain_updates(sig, "sig"))


@query(O.query([*_HOURS, O.draws(8, SEED), "mm AS (SELECT 100 AS m)", O.pads(H.PAD_A, "padA"), "xinc AS (SELECT * FROM inc)", "xsets AS (SELECT * FROM sets)", f"xcode AS ({O.codes('opm1', 'data', {})[1]})", f"xb AS ({O.buckets(2, 4, 'xcode', True)})"], "SELECT CAST(j AS INT) AS j, key, id FROM xb"))
def stream_index(spark: SparkSession, d: str) -> DataFrame:
    return streams.index_stream(spark, _days(spark, d), 8, SEED, 2, 4, 100)


@query(O.query([*_HOURS, O.draws(8, SEED), "mm AS (SELECT 100 AS m)", O.pads(H.PAD_A, "padA"), "xinc AS (SELECT * FROM inc)", "xsets AS (SELECT * FROM sets)", f"xcode AS ({O.codes('opm1', 'data', {})[1]})", f"xb AS ({O.buckets(2, 4, 'xcode', True)})"], "SELECT CAST(j AS INT) AS j, key, id FROM xb"))
def stream_index_batch(spark: SparkSession, d: str) -> DataFrame:
    return bucketing.index_rows(schemes.opm1(8, SEED, 100).data_signatures(collection(spark, d, "user_hours")), 2, 4)


@query()
def stream_probe(spark: SparkSession, d: str) -> DataFrame:
    """Documents as a stream against the benchmark's stored tables."""
    stored = bucketing.index_rows(schemes.minhash(8, SEED).data_signatures(collection(spark, d, "bench_w")), 1, 8)
    path = formats.scratch(spark, "texts")
    load(spark, d, "documents").select("doc_id", "text").write.parquet(path)
    stream = spark.readStream.schema("doc_id bigint, text string").parquet(path)
    return streams.drain(streams.probe_stream(stream, stored, 8, SEED, 1, 8), "probe").distinct()


@query("SELECT p.event_id AS p_id, c.event_id AS c_id FROM events p JOIN events c ON p.user_id = c.user_id AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR WHERE p.event_type = 'purchase' AND c.event_type = 'click'")
def stream_join(spark: SparkSession, d: str) -> DataFrame:
    return streams.drain(streams.paired(streams.event_stream(spark, _days(spark, d), 40)), "paired")
