"""Letters of any alphabet, what is learned, and tables at the edges."""

import random

import numpy as np
import pytest

pytest.importorskip("multiscale_scatter.llm")

from multiscale_scatter.llm import language_id  # noqa: E402

TONGUES = {"aa": ["olo", "mul", "opu", "lomo"], "bb": ["kit", "ikki", "tik", "ekt"]}


def lines(k, lang, n=3):
    r = random.Random(k)
    return "\n".join(" ".join(r.choice(TONGUES[lang]) + r.choice(TONGUES[lang]) for _ in range(8)) for _ in range(n))


def test_edges(spark):
    rows = [(k, lines(k, "aa" if k % 2 else "bb"), "aa" if k % 2 else "bb", 0.5, "p") for k in range(80)]
    rows += [(200, "½ ² ³", None, 0.0, ""), (201, "12 ½x", None, 0.0, ""), (202, "日本", None, 0.0, ""), (203, "_-_ ́", None, 0.0, ""), (204, lines(4, "bb", 20000), None, 0.0, ""), (205, "x" * 300000, None, 0.0, "")]
    rows += [rows[3], rows[3], (None, lines(1, "aa"), None, None, None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, score double, lang_pred string")
    out = [tuple(r) for r in language_id.identify(frame).collect()]
    assert len(out) == len(rows)
    by = {r[0]: r for r in out}
    assert by[200][2:] == by[203][2:] == ("und", 0.0) and "und" not in (by[201][2], by[202][2], by[205][2])
    assert by[204][2] == "bb" and by[None][2] == "aa" and by[None][1] is False
    assert len({r for r in out if r[0] == rows[3][0]}) == 1
    assert language_id.identify(frame.limit(0)).count() == 0


def test_learned_parts():
    rows = [(lines(k, "aa" if k % 3 else "bb"), "aa" if k % 3 else "bb") for k in range(90)]
    model = language_id.train(rows)
    assert model.first[0] > model.first[1]  # two of three texts are aa
    assert np.diag(model.transitions).min() > max(model.transitions[0, 1], model.transitions[1, 0])
    raw = np.frombuffer(b"oloolo kitkit neither", np.uint8)
    starts, ends, _, _, _ = language_id.chains(raw, np.array([0, len(raw)]))
    assert language_id.lexicon_features(model, raw, starts, ends).tolist() == [[1, 0, 0], [0, 1, 0], [0, 0, 1]]
    assert model.lexicon[0, 0] > model.lexicon[0, 1] and model.lexicon[1, 1] > model.lexicon[1, 0]


def test_gradient_of_first_weights():
    """The step of the first weights is the gradient of the chains' likelihood."""
    rng = np.random.default_rng(3)
    model = language_id.Model(["a", "b", "c"], np.zeros((1, 3), np.float32), rng.normal(size=(3, 3)), rng.normal(size=3))
    scores = rng.normal(size=(4, 3)).astype(np.float32)
    chain, place = np.zeros(4, int), np.arange(4)

    def log_norm(first):
        a = np.log(np.exp(first + scores[0]))
        for t in range(1, 4):
            a = np.log(np.exp(a[:, None] + model.transitions).sum(axis=0)) + scores[t]
        return np.log(np.exp(a).sum())

    p, _ = language_id.forward_backward(model, scores, chain, place)
    for k in range(3):
        up, down = model.first.copy(), model.first.copy()
        up[k] += 1e-4
        down[k] -= 1e-4
        assert (log_norm(up) - log_norm(down)) / 2e-4 == pytest.approx(p[0, k], abs=1e-4)
