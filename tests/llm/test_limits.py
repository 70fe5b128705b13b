"""Sizes beyond a limit give the same results: with the limit set tiny, rows equal those without."""

import numpy as np
import pytest

pytest.importorskip("multiscale_scatter.llm")

from multiscale_scatter.llm import decontamination, mixing  # noqa: E402
from test_operators import prose  # noqa: E402


def test_benchmark_slices(spark):
    items = [(k, prose(k % 9, 20 + k % 5) + " " + prose(900 + k, 12) + ". Answer: " + prose(500 + k, 5)) for k in range(70)] + [(80, None), (81, ""), (5, prose(5, 30))]
    rows = [(k, prose(k % 9, 22) + " " + prose(900 + k, 12 - k % 4) + " " + prose(500 + k, 5) + " " + prose(3000 + k, 60), "x", "y") for k in range(60)] + [(None, items[3][1], "x", "y"), (7, None, "", ""), (7, "", "", "")]
    docs = spark.createDataFrame(rows + rows[:3], "doc_id long, text string, key string, item_id string")
    tests = spark.createDataFrame(items, "item_id long, text string")
    one, many = (sorted((tuple(r) for r in decontamination.retrieve(docs, tests, 0.4, size).collect()), key=str) for size in (1 << 24, 2500))
    assert len(one) > 60 and [r[:2] for r in one] == [r[:2] for r in many]
    assert np.allclose([r[2:] for r in one], [r[2:] for r in many])
    assert decontamination.retrieve(docs, tests.limit(0), 0.4, 2500).count() == 0 and decontamination.retrieve(docs.limit(0), tests, 0.4, 2500).count() == 0
    assert decontamination.drop_contaminated(docs, tests).columns == docs.columns


@pytest.mark.parametrize("good,bad,sample", [(30, 50, 20), (7, 900, 300), (4000, 9000, 6500), (1, 3, 2)])
def test_large_draws_follow_the_law(good, bad, sample):
    """picked against the law's probabilities, and numpy's own draws."""
    from math import comb

    draw = np.random.default_rng(5)
    n = 20000
    seen = np.bincount([mixing.picked(draw, good, bad, sample) for _ in range(n)], minlength=sample + 1)
    law = np.array([comb(good, k) * comb(bad, sample - k) / comb(good + bad, sample) if k <= good and sample - k <= bad else 0 for k in range(sample + 1)])
    many = law * n > 5
    assert seen[~(law > 0)].sum() == 0
    chi = (((seen - law * n) ** 2)[many] / (law * n)[many]).sum()
    assert chi < many.sum() + 5 * np.sqrt(2 * many.sum()) + 5


def test_huge_draws():
    draw = np.random.default_rng(8)
    good, bad, sample = 3 * 10**14, 7 * 10**14, 5 * 10**14
    x = np.array([mixing.picked(draw, good, bad, sample) for _ in range(3000)], float)
    spread = np.sqrt(sample * 0.3 * 0.7 * 0.5)
    assert abs(x.mean() - sample * 0.3) < 5 * spread / np.sqrt(3000) and 0.9 < x.std() / spread < 1.1
    slots = np.array([4 * 10**12, 10**12, 0, 5, 10**9])
    parts = [mixing.shard_counts(slots, k, -(-int(slots.sum()) // 10**12), 10**12, 3) for k in range(6)]
    assert (sum(p[0] for p in parts) == slots).all() and all((parts[k + 1][1] == parts[k][1] + parts[k][0]).all() for k in range(5))


def test_draws_do_not_change_with_the_limit(monkeypatch):
    """Shards stay full and totals exact where all draws are made without numpy's generator."""
    monkeypatch.setattr(mixing, "GENERATOR_LIMIT", 0)
    counts = np.array([500, 300, 0, 13])
    parts = [mixing.shard_counts(counts, k, 9, 100, 7) for k in range(9)]
    assert (sum(p[0] for p in parts) == counts).all() and [int(p[0].sum()) for p in parts] == [100] * 8 + [13]
