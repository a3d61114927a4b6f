"""Sets against queries in tiles, against brute force; plans that hold no pairs."""

import math

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from overlapix.operators import tiles

ROOT = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def frame(spark, sets):
    return spark.createDataFrame([(i, sorted(e), len(e)) for i, e in sets.items()], "id bigint, elems array<bigint>, f int")


@pytest.fixture
def small(monkeypatch):
    """Several passes and tiles on a few rows."""
    monkeypatch.setattr(tiles, "BLOCK", 3)
    monkeypatch.setattr(tiles, "WIDE", 8)


X = {i: {(i * 7 + j * j) % 23 for j in range(i % 9 + 1)} for i in range(40)}
Q = {100 + i: {(i * 5 + j * 3) % 23 for j in range(i % 5 + 2)} for i in range(8)} | {200: X[8]}


@pytest.mark.parametrize("name", ["law_check_minhash", "law_check_normsign", "law_check_opm1", "law_check_opm2", "law_check_srp", "faster_sampling"])
def test_laws_hold_no_pairs(spark, name):
    """A join of pairs was taken for a small table and broadcast."""
    p = plan(entry.queries()[name](spark, ROOT))
    assert "Join" not in p and "MapInArrow" in p


def test_law_of_identical_sets(spark, tmp_path):
    """A law of one has no spread; the SQL gives NaN there, and the query failed."""
    v = [[1.0 if (i >> j) & 1 else -1.0 for j in range(6)] for i in (5, 9, 14)] * 30
    spark.createDataFrame(list(enumerate(v)), "vec_id bigint, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    r = entry.queries()["law_check_minhash"](spark, str(tmp_path)).first()
    assert r.n_pairs > 0 and math.isnan(r.mean_z) and 0 < r.measured <= 1


def test_estimates_hold_no_pairs(spark):
    assert "Join" not in plan(entry.queries()["estimate_overlap"](spark, ROOT))


def test_pairs_by_brute_force(spark, small):
    got = sorted(map(tuple, tiles.pairs(tiles.coded(frame(spark, X), "data"), tiles.coded(frame(spark, Q), "query")).collect()))
    assert got == sorted((q, x, len(s & t), len(s), len(t)) for q, s in Q.items() for x, t in X.items() if s & t)


@pytest.mark.parametrize("name", ["transform_l2", "transform_sign", "transform_norm", "inner_product_preserved"])
def test_identities_shuffle_no_pairs(spark, name):
    """Pairs, and padded elements, went through joins on the element and the id."""
    p = plan(entry.queries()[name](spark, ROOT))
    joins = p.count("Join")
    assert "MapInArrow" in p and joins <= (2 if name == "inner_product_preserved" else 0)


def test_changed_counts(spark, small):
    x = frame(spark, X).selectExpr("id", "elems", "array_append(elems, 99L) as one")
    q = frame(spark, Q).selectExpr("id", "elems", "if(id = 101, array_append(elems, 99L), elems) as one")
    n = tiles.changed_counts(tiles.coded(x, "data", more=("one",)), tiles.coded(q, "query", more=("one",)), (("one", "one"), ("one", "elems"))).agg({"n": "sum"}).first()[0]
    assert n == len(X)


def test_grid_of_first_tables_in_tasks(spark):
    """Pairs and tables were rows of a shuffle."""
    from overlapix.plans import catalog_hash as C

    x, q = C.sides(spark, ROOT, "turn_w", "opm1", 8 * 4, 8)
    gold = tiles.top(x, q, 50)
    got = {(r.k, r.l): (r.r, r.h5) for r in tiles.first_tables(x, q, gold, 8, 4, (5,)).collect()}
    best = {(r.q_id, r.x_id) for r in gold.where("rank <= 5").collect()}
    sig = lambda s: {r.id: (r.s0, r["p0"] if "p0" in r else None) for r in s.collect()}
    xs, qs, want = sig(x), sig(q), {}
    for qi, (b, _) in qs.items():
        for xi, (a, dead) in xs.items():
            for k in range(1, 9):
                first = next((j for j in range(4) if not dead[j] and a[j * 8 : j * 8 + k] == b[j * 8 : j * 8 + k]), None)
                if first is not None:
                    n, h = want.get((k, first + 1), (0, 0))
                    want[k, first + 1] = n + 1, h + ((qi, xi) in best)
    assert got == want and got


@pytest.mark.parametrize("name", ["ranked_minhash", "ranked_l2alsh", "interpolated_pr", "pr_curve_minhash"])
def test_lists_come_out_of_tiles(spark, name):
    """Whole lists of (query, set) were sorted; now a task gives up its best few, or counts."""
    stages = [line for line in plan(entry.queries()[name](spark, ROOT)).splitlines() if "InArrow" in line]
    assert stages and not any("q_id#" in line and "x_id#" in line and " k#" in line for line in stages)


def test_curve_in_blocks_and_stretches(spark, monkeypatch):
    """Against the sorted lists, over several blocks of queries and stretches of sets."""
    from overlapix.operators import ranking
    from overlapix.plans import catalog_hash as C

    monkeypatch.setattr(tiles, "BLOCK", 23)
    monkeypatch.setattr(tiles, "STRETCH", 100)
    cols = ["q_id", "p", "relevant_seen", "precision_", "recall"]
    ranked, gold = C.ranked(spark, ROOT, "turn_w", "opm1", (C.N_RANK,))
    want = sorted(map(tuple, ranking.pr_points(ranked, gold).select(*cols).collect()))
    assert sorted(map(tuple, C.pr_curve(spark, ROOT, "opm1").select(*cols).collect())) == want and want
    listed = sorted(map(tuple, ranked.where("p <= 20").select("q_id", "p", "x_id", "matches").collect()))
    assert sorted(map(tuple, entry.queries()["ranked_opm1"](spark, ROOT).select("q_id", "p", "x_id", "matches").collect())) == listed


def test_curve_of_more_sets_than_a_range_samples(spark, tmp_path):
    """Sets were numbered by range partitions that two branches of the plan sampled apart,
    so places were wrong as soon as there were more sets than a sample holds."""
    from overlapix.operators import ranking
    from overlapix.plans import catalog_hash as C

    rows = [(i // 8, i % 8, " ".join(f"w{(i * j * j + j * 31) % 97}" for j in range(2 + i % 7))) for i in range(6000)]
    spark.createDataFrame(rows, "conv_id bigint, turn bigint, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    cols = ["q_id", "p", "relevant_seen", "precision_", "recall"]
    ranked, gold = C.ranked(spark, str(tmp_path), "turn_w", "opm1", (C.N_RANK,))
    want, got = ranking.pr_points(ranked, gold).select(*cols), C.pr_curve(spark, str(tmp_path), "opm1").select(*cols)
    want, got = (df.withColumn("h", F.xxhash64(*cols).cast("decimal(38,0)")).groupBy().agg(F.count("*"), F.sum("h")).first() for df in (want, got))
    assert got == want and got[0] > 10_000


def test_codes_are_dealt_out_once(spark, small):
    """Every block of queries shuffled all the codes again."""
    from overlapix.operators import schemes

    x, q = tiles.coded(frame(spark, X), "data", schemes.minhash(8, 1)), tiles.coded(frame(spark, Q), "query", schemes.minhash(8, 1))
    gold = tiles.top(x, q, 3).cache()
    packed = tiles.stretches(x, len(X)).cache()
    stages = plan(tiles.places(packed, q, gold, 8)).split("InMemoryRelation")[0]
    assert "s0#" not in stages and "FlatMapGroups" not in stages
    rows, codes = ({r.id: r.s0 for r in s.collect()} for s in (x, q))
    tie = {r.id: r.tie for r in x.select("id", tiles.exact.tie_order("id")[0].alias("tie")).collect()}
    places = {(c, i): p for c, own in codes.items() for p, i in enumerate(sorted(rows, key=lambda i: (-sum(a == b for a, b in zip(rows[i], own, strict=True)), tie[i], i)), 1)}  # noqa: B023
    assert sorted(map(tuple, tiles.places(packed, q, gold, 8).collect())) == sorted((r.q_id, places[r.q_id, r.x_id]) for r in gold.collect())


@pytest.mark.parametrize("name", "cost_model law_l2 law_sampling law_srp plan_kl rho_curves rho_l2alsh rho_minhash_q rho_opm rho_opm_q rho_sampling rho_sign".split())
def test_theory_reads_tables(spark, name):
    """Curves and plans were made of constants."""
    df = entry.queries()[name](spark, ROOT)
    assert {f.rsplit("/", 1)[1] for f in df.inputFiles()} >= {"documents.parquet", "benchmark.parquet"} or "benchmark.parquet" in plan(df)


def test_classes_of_copies_keep_no_elements(spark, monkeypatch):
    """Whole sets were shuffled and written for classes, tables and verification alike."""
    from overlapix.plans import catalog_hash as C

    written, real = {}, C.kept
    monkeypatch.setattr(C, "kept", lambda df, label="kept": written.setdefault(label, df.columns) and real(df, label))
    assert C.near_duplicates(spark, ROOT).count() > 0
    assert "elems" not in written["classes"] and written["pairs"] == ["q_id", "x_id"]
