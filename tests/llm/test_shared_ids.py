"""Filters decide by id and text: other texts without an id, or under the same id, are not lost."""

import pytest

pytest.importorskip("multiscale_scatter.llm")

from multiscale_scatter.llm import decontamination, near_duplicates  # noqa: E402
from test_operators import prose  # noqa: E402

DOCS = "doc_id long, text string, source string"


def kept_of(frame):
    return sorted(((r["doc_id"], r["text"]) for r in frame.collect()), key=str)


def test_distinct_texts_stay(spark):
    a, b, c, d, e, f = (prose(900 + k, 60) for k in range(6))
    # a: with and without id; b, c: without id, b twice; d, e under one id, e near-copied; f under one id twice, one near copy
    near = f + " " + prose(950, 2)
    rows = [(1, a), (None, a), (None, b), (None, b), (None, c), (5, d), (5, e), (6, e), (4, e), (7, f), (7, near), (None, None), (None, "")]
    docs = spark.createDataFrame([(*r, "s") for r in rows], DOCS)
    out = near_duplicates.drop_near_duplicates(docs, width=2, percent=80)
    assert out.columns == docs.columns
    got = kept_of(out)
    assert [r for r in got if r[0] == 7] in ([(7, f)], [(7, near)])
    want = [(1, a), (None, b), (None, c), (5, d), (4, e), (None, None), (None, "")]
    assert [r for r in got if r[0] != 7] == sorted(want, key=str)


def test_components_of_one_id_stay(spark):
    """Two components whose smallest id is the same keep a document each."""
    a, b = prose(970, 60), prose(971, 60)
    docs = spark.createDataFrame([(1, a, "s"), (1, b, "s"), (2, a, "s"), (3, b, "s")], DOCS)
    assert kept_of(near_duplicates.drop_near_duplicates(docs, width=2, percent=80)) == sorted([(1, a), (1, b)])


def test_clean_texts_stay(spark):
    items = [(k, prose(980 + k, 30) + ". Answer: " + prose(990 + k, 6)) for k in range(4)]
    rows = [(None, items[1][1]), (None, prose(1, 50)), (None, None), (3, prose(2, 50)), (3, items[2][1]), (4, prose(3, 50))]
    docs = spark.createDataFrame([(*r, "s") for r in rows], DOCS)
    out = decontamination.drop_contaminated(docs, spark.createDataFrame(items, "item_id long, text string"))
    assert kept_of(out) == sorted([rows[1], rows[2], rows[3], rows[5]], key=str)
