"""Families with much common text, some of it too little for a link: no link is lost, and hot shingles are dealt out."""

import random

import pytest

pytest.importorskip("multiscale_scatter.llm")

from multiscale_scatter.llm import near_duplicates  # noqa: E402
from test_operators import brute_groups, prose  # noqa: E402


@pytest.mark.parametrize("share", [4096, 7])
def test_families_below_the_threshold(spark, monkeypatch, share):
    monkeypatch.setattr(near_duplicates, "SHARE", share)
    r = random.Random(3)
    base = prose(1, 100).split()
    rows = []
    for k in range(120):  # most share about 0.6 to 0.85 of their text with all the others
        own = [f"own{k // 2 if k % 3 == 0 else k}x{j}" for j in range(r.choice([2, 6, 10, 14, 30]))]
        cut = r.randrange(100)
        rows.append((k, " ".join(base[:cut] + own + base[cut:])))
    r.shuffle(rows)
    sets, group = brute_groups(rows, 2, 80)
    want = sorted((i, min(rows[j][0] for j in range(len(rows)) if group[j] == group[k])) for k, (i, _) in enumerate(rows))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((x["doc_id"], x["component_id"]) for x in near_duplicates.near_duplicates(docs, 2, 80, short=2).collect())
    assert got == want and 1 < len({c for _, c in want}) < 115


def test_all_links_alone(spark):
    """The last step by itself, from classes that are all in components of their own."""
    rows = [(k, t) for k, t in enumerate(" ".join(random.Random(k).sample(prose(5, 40).split(), 36)) for k in range(40))] + [(50, prose(5, 40)), (51, prose(5, 41))]
    grams = {i: {tuple(w[k : k + 1]) for k in range(len(w))} for i, t in rows for w in [t.split()]}
    sets = spark.createDataFrame([(i, [hash(g[0]) for g in s]) for i, s in grams.items()], "cid long, shingles array<long>")
    members = spark.createDataFrame([(7, i, len(s), i) for i, s in grams.items()], "key long, cid long, n int, component long")
    got = {(x["a"], x["b"]) for x in near_duplicates._all_links(members, sets, 80).collect()}
    want = {(a, b) for a in grams for b in grams if a < b and 100 * len(grams[a] & grams[b]) >= 80 * len(grams[a] | grams[b])}
    assert got == want and want
