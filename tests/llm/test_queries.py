"""Registered queries: the SQL twin, contracts' columns, and the pipeline."""

import pytest


def test_line_dedup_equals_sql(spark, sf, duck):
    from dp_margin.llm import linededup

    got = linededup.op5_line_dedup(spark, sf).toPandas()
    want = duck.execute(linededup.ORACLE).df()[got.columns]
    key = list(got.columns)
    assert got.astype(str).sort_values(key).reset_index(drop=True).equals(want.astype(str).sort_values(key).reset_index(drop=True))


@pytest.mark.parametrize("name, columns", [
    ("op1_telephony_audio", {"doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"}),
    ("op2_sentencepiece", {"doc_id", "n_tokens"}),
    ("op3_separator_scan", {"doc_id", "n_tokens"}),
    ("op4_secret_scan", {"doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"}),
    ("op6_language_id", {"doc_id", "lang"}),
    ("op7_minhash_near_dup", {"doc_id", "n_shingles", "component_id", "kept"}),
    ("op8_spaced_seed_decontam", {"doc_id", "contaminated"}),
    ("op10_arrow_token_files", {"doc_id", "start", "n_tokens", "ids_crc32"}),
])
def test_a_row_for_every_document(spark, sf, name, columns):
    from dp_margin.llm.queries import QUERIES

    out = QUERIES[name](spark, sf)
    assert columns <= set(out.columns)
    assert out.count() == spark.read.parquet(f"{sf}/documents.parquet").count()


def test_pipeline(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    seen = docs
    for _, stage in cp.STAGES[:-1]:
        out = stage(spark, seen, sf)
        assert out.columns == docs.columns
        assert 0 < out.count() <= seen.count()
        seen = out
    last = cp.STAGES[-1][1](spark, seen, sf)
    assert last.where("n_tokens <> size(ids)").count() == 0
    assert sorted(r.doc_id for r in cp.run(spark, sf).select("doc_id").collect()) == sorted(r.doc_id for r in last.select("doc_id").collect())


def test_native_plan_has_no_python(spark, sf):
    from dp_margin.llm.decontam import op8_spaced_seed_decontam

    text = op8_spaced_seed_decontam(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Arrow" not in text and "Cartesian" not in text
