"""Edges of operators and pipeline that other tests leave: empty tables, null ids, repeats, very long texts, native jobs."""


import pytest

pytest.importorskip("multiscale_scatter.llm")
pipeline = pytest.importorskip("corpus_pipeline")

from multiscale_scatter.llm import decontamination, quality_rules, secret_scan, shared, token_counts, url_filter  # noqa: E402
from test_operators import prose  # noqa: E402
from test_url_links import planted  # noqa: E402

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ITEMS = "item_id long, text string"


def test_pipeline_without_rows_and_ids(spark, tmp_path):
    item = prose(700, 25) + ". " + prose(800, 8) + "."
    texts = [prose(1, 60), prose(2, 60), prose(2, 60), None, "", prose(3, 40) + " " + item, prose(4, 30) + " token=abcdef123456"]
    rows = [(None, t, "en", None, None) for t in texts] + [(5, prose(5, 50), None, "s", 3)]
    for name, some in (("full", rows), ("empty", [])):
        spark.createDataFrame(some, DOCS).write.parquet(f"{tmp_path}/{name}/documents.parquet")
        spark.createDataFrame([(1, item), (2, None)] if some else [], ITEMS).write.parquet(f"{tmp_path}/{name}/benchmark.parquet")
    out = pipeline.run(spark, f"{tmp_path}/full").collect()
    # the two equal texts are one, what has no words or the item is gone
    assert sorted((r["doc_id"] is None, r["size"]) for r in out) == [(False, 50), (True, 31), (True, 60), (True, 60)]
    assert pipeline.run(spark, f"{tmp_path}/empty").count() == 0


def test_decontamination_edges(spark):
    items = [(k, prose(100 + k, 30) + ". Answer: " + prose(200 + k, 6)) for k in range(4)]
    docs = spark.createDataFrame([(1, items[2][1], "x", 7), (1, items[2][1], "x", 7), (2, "word " * 300_000 + items[0][1], "y", 8)], "doc_id long, text string, score string, item_id int")
    tests = spark.createDataFrame([(*i, "e") for i in items + items[:1]], ITEMS + ", key string")
    found = sorted((r["doc_id"], r["item_id"]) for r in decontamination.contaminated(docs, tests).collect())
    assert found == [(1, 2), (1, 2), (2, 0), (2, 0)]
    assert decontamination.drop_contaminated(docs, tests).count() == 0
    assert decontamination.contaminated(docs.limit(0), tests).count() == 0


def test_token_counts_of_one_long_word(spark):
    rows = [(1, "ab" * 400_000), (2, "x"), (2, "x"), (None, "ab" * 400_000)]
    out = {(r["doc_id"], r["n_pretokens"], r["n_tokens"]) for r in token_counts.token_counts(spark.createDataFrame(rows, "doc_id long, text string"), vocabulary={"▁": -1.0, "ab": -2.0, "x": -3.0, "▁x": -2.5}).collect()}
    assert out == {(1, 1, 400_001), (2, 1, 1), (None, 1, 400_001)}


def test_hosts_decide_about_soft_rules(spark):
    """A table-like text goes where the host's texts often are like that, and stays where it is alone."""
    table = " | ".join(prose(k, 1) for k in range(30))
    rows = [(k, prose(k, 40) if k % 2 else table + f" {k}", "tables") for k in range(400)] + [(1000 + k, prose(k, 41) if k else table, "prose") for k in range(400)]
    judged = {r["doc_id"]: r for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert judged[0]["failed"] == judged[1000]["failed"] == ["symbols"] and judged[0]["broken"] == ["symbols"] and judged[1000]["broken"] == []
    assert not judged[0]["kept"] and judged[1]["kept"] and judged[1000]["kept"]


def test_native_jobs(spark, tmp_path, monkeypatch):
    """No plan that op1 or op5 runs has Python in it, those that it writes on its way included."""
    plans = []
    real = shared.materialize

    def seen(df, name, *more, **options):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return real(df, name, *more, **options)

    for module in (shared, secret_scan, url_filter):
        monkeypatch.setattr(module, "materialize", seen)
    spark.createDataFrame(planted(), "page_id long, url string, html string, node string, alias string").write.parquet(f"{tmp_path}/pages.parquet")
    spark.createDataFrame([(1, 'user: bob password = "hunter22"'), (2, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    for run in (secret_scan.op1_secret_scan, url_filter.op5_url_filter):
        plans.append(run(spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString())
    assert len(plans) > 6
    assert not [p for p in plans if any(w in p for w in ("Python", "Arrow", "Pandas", "ExistingRDD"))]


def test_long_and_repeated_quality(spark):
    text = "same line here\n" * 100_000
    rows = [(1, text, "s"), (1, text, "s"), (2, prose(1, 30), None)]
    out = {(r["doc_id"], r["n_words"], r["n_dup_lines"], r["kept"]) for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert out == {(1, 300_000, 99_999, False), (2, 30, 0, True)}
