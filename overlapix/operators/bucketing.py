"""Hash tables of meta-hashes, and what a query finds in them.

Table j keeps, for each set, the codes j*K .. j*K+K-1 as one key.  Tables are
one long frame ``(j, key, id)``.  A row whose slice holds a code that came from
padding can meet no query and is not written.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from overlapix.functions import measures
from overlapix.operators import exact, schemes
from overlapix.plans.planner import broadcast_if_small, salted_join


def meta_hash(sig: Column, j: Column | int, k: int, portable: bool = True) -> Column:
    """The key of table ``j``: codes joined by dashes, or their 64-bit hash for production."""
    j = F.lit(j) if isinstance(j, int) else j
    part = F.slice(sig, j * k + 1, F.lit(k))
    return F.array_join(F.transform(part, lambda c: c.cast("string")), "-") if portable else F.xxhash64(part)


def index_rows(sig: DataFrame, k: int, l: int, portable: bool = True, keep_dead: bool = False) -> DataFrame:  # noqa: E741
    """``j, key, id`` of ``l`` tables of ``k`` codes; the signature holds ``k * l``."""
    rows = sig.select("id", "sig", "pad", F.explode(F.sequence(F.lit(0), F.lit(l - 1))).alias("j"))
    if not keep_dead:
        dead = F.exists(F.slice(F.coalesce("pad", F.array().cast("array<boolean>")), F.col("j") * k + 1, F.lit(k)), lambda x: x)
        rows = rows.where(~dead)
    return rows.select("j", meta_hash(F.col("sig"), F.col("j"), k, portable).alias("key"), "id")


class LshIndex:
    """Tables of a collection under a scheme; rows can be kept as a bucketed table."""

    def __init__(self, rows: DataFrame, scheme: schemes.Scheme, k: int, l: int, portable: bool = True) -> None:  # noqa: E741
        self.rows, self.scheme, self.k, self.l, self.portable = rows, scheme, k, l, portable

    @classmethod
    def build(cls, sets: DataFrame, scheme: schemes.Scheme, k: int, l: int, portable: bool = True) -> LshIndex:  # noqa: E741
        if scheme.h < k * l:
            raise ValueError("the scheme has fewer codes than the tables need")
        return cls(index_rows(scheme.data_signatures(sets), k, l, portable), scheme, k, l, portable)

    def save(self, table: str, buckets: int = 64) -> None:
        """One shuffle at write time; probes and later joins on the key then need none."""
        self.rows.write.mode("overwrite").bucketBy(buckets, "j", "key").sortBy("j", "key").saveAsTable(table)

    @classmethod
    def open(cls, spark: SparkSession, table: str, scheme: schemes.Scheme, k: int, l: int, portable: bool = True) -> LshIndex:  # noqa: E741
        return cls(spark.table(table), scheme, k, l, portable)

    def probes(self, queries: DataFrame) -> DataFrame:
        rows = index_rows(self.scheme.query_signatures(queries), self.k, self.l, self.portable)
        return rows.select("j", "key", F.col("id").alias("q_id"))

    def candidates(self, queries: DataFrame) -> DataFrame:
        """``q_id, x_id``: the union of a query's buckets over the tables."""
        data = self.rows.select("j", "key", F.col("id").alias("x_id"))
        return data.join(broadcast_if_small(self.probes(queries)), ["j", "key"]).select("q_id", "x_id").distinct()

    def verified(self, train: DataFrame, queries: DataFrame) -> DataFrame:
        """``q_id, x_id, a, fq, fx`` of candidates, by exact intersection."""
        return verify(self.candidates(queries), train, queries)

    def search(self, train: DataFrame, queries: DataFrame, t: int, measure: str = "containment") -> DataFrame:
        found = self.verified(train, queries).where("a > 0")
        scored = found.withColumn("score", exact.MEASURES[measure](F.col("a"), F.col("fq"), F.col("fx")))
        return exact.top_t(scored, t).select("q_id", F.col("rank").cast("bigint").alias("rank"), "x_id", "a")

    def join(self, train: DataFrame, other: DataFrame, t: float, measure: str = "containment") -> DataFrame:
        """Candidate pairs whose measure reaches ``t``."""
        found = self.verified(train, other)
        if measure == "containment":
            kept = found.where(F.col("a") >= F.ceil(F.lit(t) * F.col("fq") - 1e-9))
        else:
            kept = found.where(exact.MEASURES[measure](F.col("a"), F.col("fq"), F.col("fx")) >= t)
        return kept.select("q_id", "x_id", "a", "fq", "fx")

    def upsert(self, sets: DataFrame) -> LshIndex:
        """Rows of ``sets`` replace those of the same ids; other rows are not touched."""
        fresh = index_rows(self.scheme.data_signatures(sets), self.k, self.l, self.portable)
        return LshIndex(self.rows.join(sets.select("id"), "id", "left_anti").select("j", "key", "id").unionByName(fresh), self.scheme, self.k, self.l, self.portable)

    def delete(self, ids: DataFrame) -> LshIndex:
        return LshIndex(self.rows.join(ids.select("id"), "id", "left_anti").select("j", "key", "id"), self.scheme, self.k, self.l, self.portable)

    def grow(self, raw: DataFrame, m: int) -> LshIndex:
        """The index for a new bound ``m``, out of raw signatures: no element is hashed again."""
        scheme = self.scheme.with_(m=m)
        return LshIndex(index_rows(schemes.repad(raw, scheme), self.k, self.l, self.portable), scheme, self.k, self.l, self.portable)

    def stats(self) -> DataFrame:
        """``n_buckets`` by bucket size."""
        return self.rows.groupBy("j", "key").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n_buckets"))


def verify(pairs: DataFrame, train: DataFrame, queries: DataFrame) -> DataFrame:
    """Exact overlaps of given pairs: queries of proven size are broadcast, sets are joined by id."""
    q = broadcast_if_small(queries.select(F.col("id").alias("q_id"), F.col("elems").alias("qe"), F.col("f").cast("bigint").alias("fq")), 50_000)
    x = train.select(F.col("id").alias("x_id"), F.col("elems").alias("xe"), F.col("f").cast("bigint").alias("fx"))
    return pairs.join(x, "x_id").join(q, "q_id").select("q_id", "x_id", measures.overlap(F.col("qe"), F.col("xe")).cast("bigint").alias("a"), "fq", "fx")


def self_join(sets: DataFrame, scheme: schemes.Scheme, k: int, l: int, hot: int = 50_000, keep_identical: bool = True) -> DataFrame:  # noqa: E741
    """Pairs ``(id1 < id2)`` that share a bucket of a symmetric scheme.  Identical sets
    are represented once, by their least id; heavy buckets are dealt out by salt."""
    classes = sets.groupBy(F.xxhash64("elems").alias("h"), "elems").agg(F.min("id").alias("id"))
    rows = index_rows(scheme.data_signatures(classes), k, l)
    left, right = rows.select("j", "key", F.col("id").alias("id1")), rows.select("j", "key", F.col("id").alias("id2"))
    pairs = salted_join(left, right, ["j", "key"], hot).where("id1 < id2").select("id1", "id2").distinct()
    if not keep_identical:
        return pairs
    same = sets.join(classes.select("elems", F.col("id").alias("id1")), "elems").where("id > id1").select("id1", F.col("id").alias("id2"))
    return pairs.unionByName(same)


def bucket_eval(cands: DataFrame, gold: DataFrame, queries: DataFrame) -> DataFrame:
    """``q_id, reported, hits, g`` per query that has gold."""
    g = gold.groupBy("q_id").agg(F.count("*").alias("g"))
    reported = cands.groupBy("q_id").agg(F.count("*").alias("reported"))
    hits = cands.join(gold.select("q_id", "x_id"), ["q_id", "x_id"]).groupBy("q_id").agg(F.count("*").alias("hits"))
    zero = F.lit(0).cast("bigint")
    return g.join(reported, "q_id", "left").join(hits, "q_id", "left").select("q_id", F.coalesce("reported", zero).alias("reported"), F.coalesce("hits", zero).alias("hits"), "g")


def prefix_tables(xsig: DataFrame, qsig: DataFrame, kmax: int, lmax: int) -> DataFrame:
    """``q_id, x_id, k, min_l``: the first number of tables at which a pair shares a
    bucket of ``k`` codes, for every k at once.

    Table j owns a block of ``kmax`` codes; a pair meets there at (K, L) for every
    K up to the length of the blocks' common prefix.  Pairs meet by an equi-join on
    the table and the block's first code.
    """

    def blocks(sig: DataFrame, name: str, block: str) -> DataFrame:
        rows = sig.select(F.col("id").alias(name), "sig", F.coalesce("pad", F.array().cast("array<boolean>")).alias("pad"), F.explode(F.sequence(F.lit(1), F.lit(lmax))).alias("j"))
        part = rows.select(name, "j", F.slice("sig", (F.col("j") - 1) * kmax + 1, kmax).alias(block), F.slice("pad", (F.col("j") - 1) * kmax + 1, kmax).alias("dead"))
        return part.where(~F.coalesce(F.get("dead", F.lit(0)), F.lit(False))).select(name, "j", block, F.col(block)[0].alias("first"))

    met = blocks(xsig, "x_id", "xb").join(broadcast_if_small(blocks(qsig, "q_id", "qb")), ["j", "first"])
    differ = F.array_position(F.zip_with("xb", "qb", lambda a, b: a == b), False)
    lcp = met.select("q_id", "x_id", "j", F.when(differ == 0, F.lit(kmax)).otherwise(differ - 1).cast("int").alias("lcp"))
    by_k = lcp.select("q_id", "x_id", "j", F.explode(F.sequence(F.lit(1), "lcp")).alias("k"))
    return by_k.groupBy("q_id", "x_id", "k").agg(F.min("j").alias("min_l"))


def grid_eval(first: DataFrame, gold: DataFrame, kmax: int, lmax: int, ts: tuple[int, ...]) -> DataFrame:
    """``k, l, t, hits, reported`` for every (K, L, T): running sums over a histogram of ``min_l``."""
    marked = first.join(broadcast_if_small(gold.select("q_id", "x_id", "rank")), ["q_id", "x_id"], "left")
    cells = marked.groupBy("k", F.col("min_l").alias("l")).agg(F.count("*").alias("r"), *[F.count(F.when(F.col("rank") <= t, 1)).alias(f"h{t}") for t in ts])
    return grid_sums(cells, kmax, lmax, ts)


def grid_sums(cells: DataFrame, kmax: int, lmax: int, ts: tuple[int, ...]) -> DataFrame:
    """The same out of ``k, l, r, h<t>...``: how many pairs meet first in table l at K = k."""
    spark = cells.sparkSession
    grid = spark.range(1, kmax + 1).select(F.col("id").cast("int").alias("k")).crossJoin(spark.range(1, lmax + 1).select(F.col("id").cast("int").alias("l")))
    run = Window.partitionBy("k").orderBy("l").rowsBetween(Window.unboundedPreceding, 0)
    full = grid.join(F.broadcast(cells), ["k", "l"], "left").select("k", "l", *[F.coalesce(F.sum(c).over(run), F.lit(0)).cast("bigint").alias(c) for c in ("r", *(f"h{t}" for t in ts))])
    return full.select("k", "l", F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.col(f"h{t}").alias("hits")) for t in ts])).alias("x"), F.col("r").alias("reported")).select("k", "l", "x.t", "x.hits", "reported")


def best_per_recall(grid: DataFrame, gold: DataFrame, n_pairs: int, levels: tuple[float, ...]) -> DataFrame:
    """``t, level, k, l, fraction``: the cheapest (K, L) that reaches each recall.
    Ties go to the smaller K*L, then to the smaller K."""
    ts = [r.t for r in grid.select("t").distinct().collect()]
    totals = gold.agg(*[F.count(F.when(F.col("rank") <= t, 1)).alias(str(t)) for t in ts]).first()
    level = F.explode(F.array(*[F.lit(x) for x in levels]))
    wanted = F.create_map(*[x for t in ts for x in (F.lit(t), F.lit(int(totals[str(t)])))])
    reach = grid.select("k", "l", "t", "reported", (F.col("hits") / wanted[F.col("t")]).alias("recall"), level.alias("level")).where("recall >= level - 1e-12")
    best = reach.groupBy("t", "level").agg(F.min(F.struct("reported", (F.col("k") * F.col("l")).alias("kl"), "k", "l")).alias("b"))
    return best.select("t", "level", "b.k", "b.l", F.round(F.col("b.reported") / F.lit(n_pairs), 6).alias("fraction"))
