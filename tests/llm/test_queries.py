import corpus_pipeline
from overlapix.llm import queries

ROOT = "/root/testdata/sf0.001"


def test_pipeline_stages_act(spark):
    docs = spark.read.parquet(f"{ROOT}/documents.parquet")
    counts, now = [docs.count()], docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, ROOT)
        assert now.columns == docs.columns and now.schema["doc_id"].dataType == docs.schema["doc_id"].dataType, name
        counts.append(now.count())
    assert counts[0] > counts[1] > counts[2] >= counts[3] == counts[4] > 0.5 * counts[0]
    left = {r.doc_id: r for r in now.collect()}
    assert all(r.n_chars == len(r.text) for r in left.values())
    done = corpus_pipeline.STAGES[-1][1](spark, now, ROOT).collect()
    assert len(done) == counts[-1] and all(r.round_trip for r in done)
    assert not queries.decontaminate.contamination(now, spark.read.parquet(f"{ROOT}/benchmark.parquet")).where("contaminated").count()
    assert not [r for r in left.values() if any(sound for *_, sound in queries.pii.matches(r.text))]


ODD = [(1, None), (2, ""), (3, "one two"), (3, "one two"), (None, "mail a@b.example.com now"), (None, None), (7, "word " * 40_000), (8, " \n "), (9, "Ünïcode text +1 (826) 555-4081 end")]


def test_every_stage_takes_odd_rows(spark):
    """Nulls, empty and very long texts, rows that repeat, clashing columns and empty tables at each stage."""
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, fp bigint, hit string"
    docs = spark.createDataFrame([(i, t, None, "s", len(t or ""), 2.0, 5, "h") for i, t in ODD], schema)
    for name, stage in corpus_pipeline.STAGES:
        done = stage(spark, docs, ROOT)
        rows = done.collect()
        assert len(rows) <= len(ODD) and stage(spark, docs.limit(0), ROOT).count() == 0, name
        if name != corpus_pipeline.STAGES[-1][0]:
            assert done.columns == docs.columns
            assert all((r.score, r.fp, r.hit) == (2.0, 5, "h") for r in rows)
        else:
            assert all(r.round_trip for r in rows)
        if name not in ("quality classifier", "SimHash near-dedup"):
            assert len(rows) == len(ODD), name
    kept = sorted((r.doc_id for r in corpus_pipeline.near_dedup(spark, docs, ROOT).collect()), key=repr)
    assert kept == [1, 3, 7, 9, None, None]
    texts = {r.doc_id: r.text for r in corpus_pipeline.personal_data(spark, docs, ROOT).collect()}
    assert texts[9] == "Ünïcode text <PHONE> end" and texts[1] is None and len(texts[7]) == 200_000


def test_every_query_has_its_columns(spark):
    want = {
        "op1": "doc_id fingerprint component_id", "op2": "page_id url text n_chars", "op3": "doc_id n_tokens", "op4": "vec_id n_links component_id kept",
        "op5": "doc_id n_words n_hit n_items items_sha256 contaminated", "op6": "doc_id held_out score predicted", "op7": "doc_id held_out n_tokens n_known train_tokens base_score score",
        "op8": "doc_id n_tokens ids_sha256 decoded_sha256", "op9": "doc_id start n_tokens ids_crc32", "op10": "doc_id n_email n_ip n_card n_phone base_sha256 spans",
    }
    for name, f in queries.QUERIES.items():
        df = f(spark, ROOT)
        assert df.columns == want[name.split("_")[0]].split(), name
