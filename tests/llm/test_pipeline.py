"""The pipeline's stages against brute force, and the registry."""

import random
import re

import pytest

pytest.importorskip("multiscale_scatter.llm")
pipeline = pytest.importorskip("corpus_pipeline")

from test_operators import brute_counts, brute_groups, family, prose  # noqa: E402

SMALL = "/root/testdata/sf0.001"


def test_stages(spark, tmp_path):
    items = [(k, prose(700 + k, 25) + ". " + prose(800 + k, 8) + ".") for k in range(5)]
    texts = family(1, 6, 8) + [prose(k, 90) for k in range(20, 40)] + ["too short", None, prose(50, 60) + " " + items[2][1] + " " + prose(51, 20), prose(52, 40) + " token=abcdef123456 " + prose(53, 20)]
    rows = [(k, t, "en", f"s{k % 2}", len(t or "")) for k, t in enumerate(texts)]
    random.Random(2).shuffle(rows)
    cols = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, cols).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    keep = rows
    seen = {}
    for name, stage in pipeline.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        seen[name] = docs.toPandas()
        if name != "mixing":
            assert docs.columns == [c.split()[0] for c in cols.split(", ")]
    keep = [r for r in keep if (c := brute_counts(r[1] or ""))[0] >= 10 and 100 * c[4] <= 20 * c[0]]
    assert sorted(seen["quality rules"].doc_id) == sorted(r[0] for r in keep)
    _, group = brute_groups([(r[0], r[1]) for r in keep], 5, 80)
    keep = [r for k, r in enumerate(keep) if r[0] == min(keep[j][0] for j in range(len(keep)) if group[j] == group[k])]
    assert sorted(seen["near duplicates"].doc_id) == sorted(r[0] for r in keep)
    keep = [r for r in keep if not any(t in r[1] for _, t in items)]
    assert sorted(seen["decontamination"].doc_id) == sorted(r[0] for r in keep)
    want = {r[0]: re.sub(r"token=\w+", "[SECRET]", r[1]) for r in keep}
    assert dict(zip(seen["secret scan"].doc_id, seen["secret scan"].text)) == want
    mixed = seen["mixing"]
    assert sorted(mixed.doc_id) == sorted(want) and (mixed.taken <= 3 * mixed["size"]).all()


def test_run_and_registry(spark):
    out = pipeline.run(spark, SMALL)
    assert out.count() > 50 and [len(s) for s in pipeline.STAGES] == [2] * 5
    from multiscale_scatter.llm import registry

    assert {int(re.match(r"op(\d+)_", n)[1]) for n in registry.QUERIES} == set(range(1, 11))
    native = registry.QUERIES["op1_secret_scan"](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in native and "Arrow" not in native and "Pandas" not in native
