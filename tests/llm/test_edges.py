"""The edge contract of every operator: null, repeated and missing ids, odd and very long texts, clashing names, empty tables, broadcast limits."""

import collections

import pytest
from pyspark.sql import functions as F

from dp_margin.llm import common, linededup, pieces, wrappers
from dp_margin.llm.queries import QUERIES

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "a long line of words and numbers 1234 " * 60_000 + "\n" + "x" * 300_000
ROWS = [(1, "first text with some words in it"), (1, "another text under the same id"), (None, "a text without an id"), (None, None), (2, None), (3, ""), (4, " \t\r\n\x0b\x0c "), (5, LONG), (6, "first text with some words in it"), (6, "first text with some words in it"), (7, "a\u00a0b \u2028 \U0001f600 password=abcdefghijkl")]


def folder(spark, tmp_path, rows, pages=(), items=((1, "a benchmark passage of words that no document has in it anywhere at all"),)):
    frame = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOCS)
    # own columns whose names the operators use themselves
    for c in ("dm_ids", "dm_n_lines", "dm_n_dropped", "dm_decoded", "dm_key", "gone", "parts", "shard", "rep", "bits", "own_0", "seed", "shift", "host", "declared", "hint", "h"):
        frame = frame.withColumn(c, F.lit("own"))
    frame.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(list(items), "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame(list(pages), "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    return str(tmp_path)


@pytest.mark.parametrize("name", sorted(q for q in QUERIES if q.startswith("op") and not q.startswith("op9")))
def test_rows_of_every_kind(spark, tmp_path, name):
    sf = folder(spark, tmp_path, ROWS)
    got = QUERIES[name](spark, sf).collect()
    assert collections.Counter(r.doc_id for r in got) == collections.Counter(i for i, _ in ROWS)


@pytest.mark.parametrize("name", sorted(q for q in QUERIES))
def test_empty_tables(spark, tmp_path, name):
    assert QUERIES[name](spark, folder(spark, tmp_path, [], items=[])).collect() == []


def test_pages_of_every_kind(spark, tmp_path):
    long = "<article>" + "<p>a paragraph of the page</p><hr>" * 30_000 + "</article>"
    rows = [(1, "http://a.example/1", "<p>one</p>"), (1, "http://a.example/2", "<p>two</p>"), (None, None, None), (2, "", ""), (3, "no url", long)]
    got = collections.Counter((r.page_id, r.n_chars) for r in wrappers.op9_html_wrappers(spark, folder(spark, tmp_path, [], rows)).collect())
    assert got == collections.Counter([(1, 3), (1, 3), (None, 0), (2, 0), (3, 30_000 * 23 + 29_999 * 2)])


def test_pipeline_of_odd_and_of_no_rows(spark, tmp_path):
    import corpus_pipeline as cp

    sf = folder(spark, tmp_path / "odd", ROWS)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for _, stage in cp.STAGES[:-1]:
        docs = common.materialise(stage(spark, docs, sf))
        assert docs.columns[:5] == ["doc_id", "text", "lang", "source", "n_chars"] and docs.where("dm_ids <> 'own' OR h <> 'own'").isEmpty()
    assert cp.STAGES[-1][1](spark, docs, sf).count() == docs.count() > 0
    assert cp.run(spark, folder(spark, tmp_path / "none", [], items=[])).count() == 0


@pytest.mark.parametrize("limit", [1 << 26, -1])
def test_own_columns_of_clashing_names(spark, limit):
    d = spark.createDataFrame([(1, "x\nx", "a", "b", "c")], "doc_id long, text string, dm_n_lines string, DM_N_DROPPED string, own_1 string")
    out = linededup.apply_lines(d, linededup.build_state(d, 1), limit=limit)
    assert out.columns == [*d.columns, "dm_n_lines_", "dm_n_dropped_"] and out.first()[2:] == ("a", "b", "c", 2, 2)
    out = pieces.encode_stage(d.withColumn("dm_ids", F.lit("own")))
    assert out.columns[-4:] == ["dm_ids_", "dm_n_tokens", "dm_ids_crc32", "dm_decoded"] and out.first().dm_ids == "own"


def test_broadcasts_are_bounded_by_bytes(spark):
    d = spark.createDataFrame([(1, "x" * 1000, [1, 2]), (2, None, None)], "a long, b string, c array<long>")
    assert 1000 < common.estimated_bytes(d) < 1400 and common.estimated_bytes(d.limit(0)) == 0
    plan = lambda df: d.join(df, "a")._jdf.queryExecution().optimizedPlan().toString()
    assert "broadcast" in plan(common.small_or_plain(d)) and "merge" in plan(common.small_or_plain(d, 100))


@pytest.mark.parametrize("small", [True, False])
def test_results_do_not_depend_on_broadcasts(spark, tmp_path, monkeypatch, small):
    sf = folder(spark, tmp_path, [(i, f"{'benchmark words of this passage that are quite many in all here now ' if i % 3 == 0 else ''}text {i // 2} of row {i % 5} and more words {i // 2}") for i in range(40)], items=[(1, "benchmark words of this passage that are quite many in all here now")])
    want = {n: sorted(map(str, QUERIES[n](spark, sf).collect())) for n in ("op6_language_id", "op7_minhash_near_dup", "op8_spaced_seed_decontam")}
    if not small:
        monkeypatch.setattr(common.small_or_plain, "__defaults__", (-1,))
        assert {n: sorted(map(str, QUERIES[n](spark, sf).collect())) for n in want} == want


def test_a_cluster_needs_a_shared_folder():
    class Conf:
        def get(self, key, default=None):
            return {"spark.master": "yarn"}.get(key, default)

    class Session:
        conf = Conf()

    with pytest.raises(ValueError):
        common.shared_dir(Session())
