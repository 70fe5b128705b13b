"""The corpus operators on small fixtures: defined cases, and brute force."""

import hashlib
import itertools
import random
import re
from collections import Counter

import numpy as np
import pytest

pytest.importorskip("multiscale_scatter.llm")

from multiscale_scatter.llm import decontamination, html_text, language_id, mixing, near_duplicates, quality_rules, secret_scan, substring_dedup, suffix_sort, textvec, token_counts, url_filter  # noqa: E402
from multiscale_scatter.llm.shared import components  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, `key` string, cid long, kept int, spans string, size string, rank string, bad_id long"
WORDS = "the of river stone cloud ember quiet lantern meadow copper signal harbor winter orchard velvet thunder".split()


def prose(seed, n):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + str(r.randrange(400)) for _ in range(n))


def edge_rows():
    a, b = prose(1, 80), prose(2, 60)
    changed = a.replace(a.split()[40], "CHANGED")
    texts = [
        (1, a), (2, a), (3, changed), (4, None), (5, ""), (6, " \n\t "), (7, "one"), (8, "ONE"), (9, b + "\n" + b), (10, prose(3, 3000)), (None, prose(4, 20)), (11, b), (11, b),
        (12, "é" * 70 + " " + "日本語 " * 30), (13, "x" * 300), (14, "x" * 49), (15, None), (16, prose(60, 40)), (16, prose(60, 40)),
    ]
    return [(i, t, "en" if k % 2 else None, None if k % 3 == 0 else f"s{k % 2}", None if t is None else len(t), "k", 1, 0, "s", "z", "r", 7) for k, (i, t) in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(edge_rows(), SCHEMA)


def pairs(rows):
    return [(r[0], r[1] or "") for r in rows]


# words and suffixes -------------------------------------------------------------------------------------


def test_words_and_hashes():
    import pyarrow as pa

    texts = ["a bb\tccc", "", None, " \n", "no\xa0break x", "a bb\tccc"]
    got, hashes = [], []
    for _, _, raw, at in textvec.pieces(pa.array(texts), limit=8):
        s, e, n = textvec.word_bounds(raw, at)
        h = textvec.span_hashes(raw, s, e)
        k = np.cumsum(n)
        for lo, hi in zip(k - n, k):
            got.append([raw[s[j] : e[j]].tobytes() for j in range(lo, hi)])
            hashes.append(h[lo:hi].tolist())
    assert got == [(t or "").encode().split() for t in texts]
    assert hashes[0] == hashes[5] and len(set(itertools.chain(*hashes))) == 5


def test_suffix_array_brute_force():
    r = random.Random(7)
    for _ in range(150):
        t = np.array([r.randrange(r.choice([1, 2, 4])) for _ in range(r.randrange(1, 50))])
        order = suffix_sort.suffix_array(t, 64)
        assert list(order) == sorted(range(len(t)), key=lambda i: tuple(t[i:]))
        common = suffix_sort.neighbour_prefixes(t, order)
        for j in range(1, len(t)):
            a, b = t[order[j] :], t[order[j - 1] :]
            n = 0
            while n < min(len(a), len(b)) and a[n] == b[n]:
                n += 1
            assert common[j] == n


# 1 ------------------------------------------------------------------------------------------------------


def test_secret_scan(spark):
    key = "AKIA" + "ABCDEFGH12345678"
    far = "word " * 200
    texts = [
        (1, f"password = hunter22 and token=ab then {key}"), (2, f"pwd=abcd {far}"), (3, f"pwd=abcd user: someone {far} pwd=zzzz"),
        (4, "see https://host.example/x for more"), (5, "https://host.example/x secret: abcdefg"), (6, None), (7, ""), (8, "é" * 10 + " deadbeefdeadbeefdeadbeef"),
        (8, "other"), (None, "token=abcdefgh"), (9, "password=token = secretvalue"), (9, "password=token = secretvalue"),
    ]
    got = {}
    for r in secret_scan.scan(spark.createDataFrame(texts, "doc_id long, text string")).collect():
        got.setdefault(r["doc_id"], []).append([(s["kind"], s["start"], s["end"]) for s in r["spans"]])
    assert [k for k, *_ in got[1][0]] == ["assign", "access"]
    assert got[2] == [[]] and [k for k, *_ in got[3][0]] == ["weak_assign", "account"]
    assert got[4] == [[]] and {k for k, *_ in got[5][0]} == {"endpoint", "assign"}
    assert got[6] == got[7] == [[]] and sorted(got[8]) == [[], [("hex", 11, 35)]]
    assert got[None] == [[("assign", 0, 14)]] and got[9] == [[], []]
    out = {r["doc_id"]: r["text"] for r in secret_scan.redact(spark.createDataFrame([(1, texts[0][1], 5), (2, None, 0)], "doc_id long, text string, spans int")).collect()}
    assert out[1] == "[SECRET] and token=ab then [SECRET]" and out[2] is None


def test_secret_many_matches(spark):
    text = " ".join(f"token=abcdef{k}" for k in range(3000))
    spans = secret_scan.scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()["spans"]
    want = [(m.start(), m.end()) for m in re.finditer(r"token=\w+", text)]
    assert [(s["start"], s["end"]) for s in spans] == want


def test_redact_keeps_rows(docs):
    assert secret_scan.redact(docs).columns == docs.columns
    assert secret_scan.redact(docs).count() == docs.count()
    assert secret_scan.scan(docs.limit(0)).count() == 0


# 2 ------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize(
    "page,text",
    [
        ("", ""),
        ("<p>a<p>b", "a\n\nb"),
        ("<ul><li>a<li>b<ul><li>c</ul></ul>", "- a\n- b\n  - c"),
        ("<ol start=4><li>x</li><li value=9>y<li>z</ol>", "4. x\n9. y\n10. z"),
        ("<table><tr><td>a<td>bb<tr><td>ccc<td>d</table>", "a    bb\nccc  d"),
        ("<style>.h{display:none}</style><div class=h>no</div><div hidden>no</div>yes<script>var a='<p>'</script>", "yes"),
        ("<div style='visibility:hidden'>a<b style='visibility:visible'>b</b></div>", "b"),
        ("<pre>  x\n y</pre>z&amp;&lt;", "  x\n y\n\nz&<"),
        ("a<br>b<hr>c", "a\nb\n\n---\n\nc"),
        ("<title>t</title><body><h1>H</h1>text <!-- no --> more", "H\n\ntext more"),
        ("<td>loose</td> < 5 <b>x", "loose\n< 5 x"),
        ("<select><option>a<option>b</select>", "a\nb"),
    ],
)
def test_html(page, text):
    assert html_text.render(page) == text


def test_html_keeps_words(spark):
    deep = "<div>" * 3000 + "core" + "</div>" * 3000
    assert html_text.render(deep) == "core"
    pages = spark.createDataFrame([(1, None, "u"), (2, deep, "u"), (None, "<p>x", "u")], "page_id long, html string, text string")
    assert sorted((r["page_id"] or 0, r["text"]) for r in html_text.extract_text(pages).collect()) == [(0, "x"), (1, ""), (2, "core")]


# 3 ------------------------------------------------------------------------------------------------------


def test_decontamination(spark):
    items = [(k, prose(100 + k, 30) + ". Answer: " + prose(200 + k, 6)) for k in range(20)] + [(50, None), (51, ""), (52, prose(300, 130))]
    rows = [(k, prose(k, 150)) for k in range(30)]
    rows[3] = (3, prose(3, 90) + " " + items[5][1].upper() + " " + prose(3, 90))
    rows[4] = (4, prose(4, 2000) + " " + items[7][1])
    rows[5] = (5, prose(5, 50) + " " + items[9][1].split(" Answer")[0] + " " + prose(6, 50))
    rows[6] = (6, items[22][1])
    rows += [(None, items[1][1]), (7, None), (8, "")]
    found = decontamination.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert sorted((r["doc_id"] or -1, r["item_id"]) for r in found.collect()) == [(-1, 1), (3, 5), (4, 7), (6, 52)]
    none = decontamination.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([], "item_id long, text string"))
    assert none.count() == 0


def test_search_equals_scoring_all():
    """The walk by pivots and block bounds loses no unit above the threshold."""
    import pyarrow as pa

    items = [(k, prose(k % 7, 25 + k % 5) + " " + prose(900 + k, 12)) for k in range(60)]
    index = decontamination.build_index(items, 0.4)
    texts = [prose(k % 7, 40) + " " + prose(900 + 2 * k, 12) for k in range(25)]
    batch = pa.RecordBatch.from_arrays([pa.array(range(25), pa.int64()), pa.array(range(25), pa.int64()), pa.array(texts)], names=["doc_id", "key", "text"])
    got = {(d, i): s for b in decontamination._search(index)(iter([batch])) for d, i, s in zip(*(b.column(c).to_pylist() for c in ("doc_id", "item_id", "score")))}
    want = {}
    for d, text in enumerate(texts):
        words = decontamination._words(text)
        for p in range(max(-(-len(words) // decontamination.STRIDE) - 1, 1)):
            part = set(words[p * decontamination.STRIDE : (p + 2) * decontamination.STRIDE].tolist())
            score = Counter()
            for t, h in enumerate(index.terms.tolist()):
                if h in part:
                    for k in range(index.first[t], index.first[t + 1]):
                        score[int(index.unit[k])] += index.impact[k]
            for u, s in score.items():
                if s >= 0.4 - 1e-9:
                    key = (d, index.item_ids[index.item_of[u]])
                    want[key] = max(want.get(key, 0), s)
    assert want and got.keys() == want.keys()
    assert all(got[k] == pytest.approx(min(want[k], 1)) for k in want)


@pytest.mark.parametrize("threshold", [0.1, 0.3, 0.6])
def test_walk_over_many_units(monkeypatch, threshold):
    """Frequent terms in many blocks: every unit above the threshold, and none twice."""
    import numpy as np

    monkeypatch.setattr(decontamination, "PASSAGES", 64)
    draw = np.random.default_rng(3)
    items = [(k, " ".join(f"w{min(x, 400)}" for x in draw.zipf(1.3, 30))) for k in range(500)]
    index = decontamination.build_index(items, threshold)
    queries = [np.unique(draw.integers(0, len(index.terms), draw.integers(0, 60))) for _ in range(150)]
    queries += [np.unique(np.searchsorted(index.terms, decontamination._words(items[k][1]))) for k in range(100)] + [np.arange(len(index.terms))]
    begin = np.concatenate(([0], np.cumsum([len(x) for x in queries])))
    got = decontamination.search_passages(index, begin, np.concatenate(queries))
    want = {}
    for k, terms in enumerate(queries):
        has = np.isin(index.term[:-1], terms)
        score = np.bincount(index.unit[:-1][has], index.impact[:-1][has], len(items))
        want |= {(k, int(u)): score[u] for u in np.flatnonzero(score >= threshold - 1e-9)}
    assert len(got[0]) == len(want) > 100
    assert all(s == pytest.approx(want[k, u]) for k, u, s in zip(*(x.tolist() for x in got)))


# 4 ------------------------------------------------------------------------------------------------------


def brute_counts(text):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", text) if w]
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = [tuple(words[k : k + 5]) for k in range(len(words) - 4)]
    many, cover = Counter(grams), set()
    for k, g in enumerate(grams):
        if many[g] > 1:
            cover.update(range(k, k + 5))
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(cover)


def test_quality_counts(docs):
    want = sorted((i or 0, *brute_counts(t)) for i, t in pairs(edge_rows()))
    got = sorted((r["doc_id"] or 0, r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in quality_rules.judge(docs).collect())
    assert got == want
    assert quality_rules.keep_good(docs).columns == docs.columns
    assert quality_rules.judge(docs.limit(0)).count() == 0


def test_bad_host(spark):
    rows = [(k, prose(k, 40) if k % 10 else "short", "good") for k in range(200)] + [(1000 + k, "short" if k % 10 else prose(k, 40), "bad") for k in range(200)]
    rows += [(5000, "short", "tiny"), (5001, prose(1, 30), "tiny")]
    out = {r["doc_id"]: r for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert out[1]["kept"] and not out[0]["kept"] and not out[1010]["kept"] and not out[1010]["base_failed"]
    assert 0.1 < out[5000]["host_rate"] < 0.9


# 5 ------------------------------------------------------------------------------------------------------


def test_url_filter(spark):
    canonical = '<link rel="canonical" href="{}">'
    rows = [
        (1, "http://a.net/x", None), (2, "http://b.example.net/en/x", ""), (3, "HTTP://C.Example.COM/de/y?q#f", None), (4, "https://d.org/fr/1", None), (5, "nothing", None), (6, None, "<p>"),
        (7, "http://plain.org/p", canonical.format("http://a.net/x")), (8, "http://chain.org/1", canonical.format("http://plain.org/p")), (9, "http://free.org/1", canonical.format("http://d.org/fr/1")),
        (10, "http://both.org/1", canonical.format("http://free.org/1") + '<meta http-equiv="refresh" content="0; url=http://e.net/z">'), (11, "http://plain.org/p#top", None), (12, "http://evilnet/x", None),
        (13, "http://x.org", None), (13, "http://x.org", None),
    ]
    out = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.judge_urls(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert out[1] == ("a.net", "/x", "net/", "block") and out[2][2:] == ("example.net/en/", "allow")
    assert out[3] == ("c.example.com", "/de/y", "example.com/de/", "block") and out[4][2:] == ("org/fr/", "allow")
    assert out[5] == out[6] == ("", "", None, "allow")
    assert out[7][3] == out[8][3] == out[11][3] == "block" and out[9][3] == out[10][3] == "allow"
    assert out[12] == ("evilnet", "/x", None, "allow")
    assert url_filter.judge_urls(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


@pytest.mark.parametrize("one_task", [0, 10_000])
def test_components(spark, one_task):
    r = random.Random(3)
    edges = [(r.randrange(120), r.randrange(120)) for _ in range(90)] + [(200 + k, 201 + k) for k in range(40)] + [(500, k) for k in range(600, 640)] + [(7, 7)]
    parent = {n: n for e in edges for n in e}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        p, q = sorted((find(a), find(b)))
        parent[q] = p
    linked = {n for e in edges if e[0] != e[1] for n in e}
    got = {x["node"]: x["component"] for x in components(spark.createDataFrame(edges, "a long, b long"), one_task).collect()}
    assert got == {n: find(n) for n in linked}
    assert components(spark.createDataFrame([], "a long, b long"), one_task).count() == 0


# 6 ------------------------------------------------------------------------------------------------------


def brute_groups(rows, width, percent):
    sets = []
    for _, t in rows:
        w = t.encode().lower().split()
        sets.append({tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set())
    group = list(range(len(rows)))

    def find(x):
        while group[x] != x:
            x = group[x]
        return x

    for a, b in itertools.combinations(range(len(rows)), 2):
        if sets[a] and sets[b]:
            n = len(sets[a] & sets[b])
            if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
                p, q = sorted((find(a), find(b)))
                group[q] = p
    return sets, [find(k) for k in range(len(rows))]


def family(seed, n, edits):
    """A text and copies with a few words changed."""
    r = random.Random(seed)
    base = prose(seed, 120).split()
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(r.randrange(edits)):
            w[r.randrange(len(w))] = f"new{r.randrange(10**6)}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("short,width", [(64, 2), (1, 2), (64, 5)])
def test_near_duplicates(spark, short, width):
    texts = [t for s in range(5) for t in family(s, 14, 24)] + family(9, 70, 14) + [None, "", "one", "ONE", "two words", prose(5, 400)]
    rows = list(enumerate(texts, 1))
    random.Random(1).shuffle(rows)
    rows = [(i, t) for i, t in rows] + [rows[0]]
    flat = [(i, t or "") for i, t in rows]
    sets, group = brute_groups(flat, width, 80)
    want = sorted((i, len(sets[k]), min(flat[j][0] for j in range(len(flat)) if group[j] == group[k]) if sets[k] else i) for k, (i, _) in enumerate(flat))
    out = near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width, 80, short=short).collect()
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in out) == want
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in out)


def test_near_duplicates_edges(docs):
    out = near_duplicates.near_duplicates(docs, 2, 80).collect()
    by = {}
    for r in out:
        by.setdefault(r["doc_id"], []).append((r["component_id"], r["kept"]))
    assert by[2] == [(1, False)] and by[3] == [(1, False)] and by[8] == [(7, False)] and by[4] == [(4, True)] and by[11] == [(9, False)] * 2 and by[16] == [(16, True)] * 2
    assert len(out) == docs.count()
    kept = near_duplicates.drop_near_duplicates(docs, width=2, percent=80)
    ids = Counter(r["doc_id"] for r in kept.collect())
    assert ids[16] == 1 and ids[2] == ids[3] == ids[11] == 0 and ids[4] == ids[5] == ids[6] == ids[None] == 1 and kept.columns == docs.columns
    assert near_duplicates.near_duplicates(docs.limit(0)).count() == 0


# 7 ------------------------------------------------------------------------------------------------------


def test_mixing(spark, docs):
    rows = [(k, prose(k, 30 + k % 50), f"s{k % 6}" if k % 13 else None) for k in range(600)] + [(7000, prose(1, 5), "tiny"), (7001, None, "s0"), (7002, prose(2, 9000), "s1")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, source string")
    mixed = mixing.mix(frame, block_words=16, shard_slots=64)
    out = mixing.taken(mixed).toPandas()
    assert sorted(out.doc_id) == sorted(r[0] for r in rows)
    assert (out.taken <= 3 * out["size"]).all()
    total = out["size"].sum()
    names = sorted({r[2] for r in rows}, key=lambda s: (s is None, s or ""))
    size = {n: sum(len((t or "").split()) for _, t, s in rows if s == n) for n in names}
    weight = {n: (5, 2, 1)[k % 3] for k, n in enumerate(names)}
    target, free = {}, set(names)
    while True:  # water filling by hand
        left = total - sum(target.values())
        share = {n: left * weight[n] / sum(weight[m] for m in free) for n in free}
        over = {n for n in free if share[n] >= 3 * size[n]}
        if not over:
            target |= share
            break
        target |= {n: 3 * size[n] for n in over}
        free -= over
    for n in names:
        mine = out[out.source.isna()] if n is None else out[out.source == n]
        assert mine.target.iloc[0] == pytest.approx(target[n])
        assert mine.taken.sum() == pytest.approx(target[n], abs=33, rel=0.02)
    slots = mixed.slots.toPandas()
    full = slots.groupby("shard").size()
    assert (full.iloc[:-1] == 64).all() and not slots.duplicated(["shard", "position"]).any()
    assert mixing.taken(mixing.mix(frame, block_words=16, shard_slots=64)).exceptAll(mixing.taken(mixed)).count() == 0
    assert mixing.taken(mixing.mix(docs)).count() == docs.count() and mixing.taken(mixing.mix(docs.limit(0))).count() == 0


def test_permutation():
    for n in (1, 2, 3, 10, 1000):
        assert sorted(mixing.permuted(np.arange(n), np.full(n, n), np.full(n, 99))) == list(range(n))
    counts = np.array([500, 300, 0, 13])
    parts = [mixing.shard_counts(counts, k, 9, 100, 7) for k in range(9)]
    assert (sum(p[0] for p in parts) == counts).all() and [int(p[0].sum()) for p in parts] == [100] * 8 + [13]
    assert all((parts[k + 1][1] == parts[k][1] + parts[k][0]).all() for k in range(8))


# 8 ------------------------------------------------------------------------------------------------------


def test_language(spark):
    import zlib

    tongues = {"aa": ["olo", "mul", "opu", "lomo"], "bb": ["kit", "ikki", "tik", "ekt"]}
    rows = []
    for k in range(120):
        lang = "aa" if k % 2 else "bb"
        r = random.Random(k)
        rows.append((k, "\n".join(" ".join(r.choice(tongues[lang]) + r.choice(tongues[lang]) for _ in range(8)) for _ in range(3)), lang))
    rows += [(500, None, "aa"), (501, "123 !!", "bb"), (502, "", None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    out = {r["doc_id"]: r for r in language_id.identify(frame).collect()}
    assert all(out[i]["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i, *_ in rows)
    held = [(i, lang) for i, t, lang in rows if t and lang and out[i]["held_out"] and i < 500]
    assert held and all(out[i]["lang_pred"] == lang for i, lang in held)
    assert [out[k]["lang_pred"] for k in (500, 501, 502)] == ["und"] * 3 and all(0 <= r["score"] <= 1 for r in out.values())
    model = language_id.train([(t, lang) for _, t, lang in rows[:120]])
    mixed = language_id.label_words(model, rows[1][1].split("\n")[0] + " " + rows[2][1].split("\n")[0])
    assert [x[1] for x in mixed] == ["aa"] * 8 + ["bb"] * 8
    assert {r["lang_pred"] for r in language_id.identify(frame.withColumn("lang", __import__("pyspark").sql.functions.lit(None).cast("string"))).collect()} == {"und"}


def test_forward_backward_brute_force():
    rng = np.random.default_rng(2)
    model = language_id.Model(["a", "b"], np.zeros((1, 2), np.float32), rng.normal(size=(2, 2)), rng.normal(size=2))
    scores = rng.normal(size=(5, 2)).astype(np.float32)
    chain, place = np.array([0, 0, 0, 1, 1]), np.array([0, 1, 2, 0, 1])
    p, moves = language_id.forward_backward(model, scores, chain, place)
    want_moves = np.zeros((2, 2))
    for rows in ([0, 1, 2], [3, 4]):
        total, marginal, pairs_ = 0, np.zeros((len(rows), 2)), np.zeros((2, 2))
        for ys in itertools.product((0, 1), repeat=len(rows)):
            w = np.exp(model.first[ys[0]] + sum(scores[r, y] for r, y in zip(rows, ys)) + sum(model.transitions[a, b] for a, b in zip(ys, ys[1:])))
            total += w
            for k, y in enumerate(ys):
                marginal[k, y] += w
            for a, b in zip(ys, ys[1:]):
                pairs_[a, b] += w
        assert p[rows] == pytest.approx(marginal / total, abs=1e-5)
        want_moves += pairs_ / total
    assert moves == pytest.approx(want_moves, abs=1e-5)


# 9 ------------------------------------------------------------------------------------------------------


def brute_dedup(rows, length=50):
    out, seen = [], {}
    for i, t in rows:
        b = t.encode()
        for p in range(len(b) - length + 1):
            seen.setdefault(b[p : p + length], []).append(i if i is not None else 1 << 62)
    least = {w: min(v) for w, v in seen.items()}
    for i, t in rows:
        b = t.encode()
        gone = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if least[b[p : p + length]] < (i if i is not None else 1 << 62):
                gone[p : p + length] = b"\1" * length
        kept = bytes(x for x, g in zip(b, gone) if not g)
        spans = sum(1 for k in range(len(b)) if gone[k] and (k == 0 or not gone[k - 1]))
        out.append((i or 0, len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def digest(frame):
    return sorted((r["doc_id"] or 0, r["n_bytes"], sum(s["end"] - s["start"] for s in r["removed"]), len(r["removed"]), r["kept_sha256"]) for r in frame.collect())


def test_substring_dedup(spark, docs):
    assert digest(substring_dedup.dedup_substrings(docs)) == brute_dedup(pairs(edge_rows()))
    shared = [prose(50 + k, 14) for k in range(6)]
    r = random.Random(4)
    rows = [(k, " ".join([prose(1000 + k, r.randrange(30)), r.choice(shared)[r.randrange(20) :], prose(2000 + k, 9), r.choice(shared), "a" * r.randrange(120)])) for k in range(120)]
    r.shuffle(rows)
    assert digest(substring_dedup.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string"))) == brute_dedup(rows)
    assert substring_dedup.dedup_substrings(docs.limit(0)).count() == 0


# 10 -----------------------------------------------------------------------------------------------------


def test_piece_scores(spark):
    """Scores are the pieces' shares in the file's own segmentation of all words."""
    import math

    texts = ["the river the", None, "", "meadow river", "the river the"]
    file = token_counts._processor(token_counts.DEFAULT_MODEL)
    uses = Counter(p for t in texts for w in (t or "").split() for p in file.encode(w, out_type=str))
    got = token_counts.estimate(spark.createDataFrame([(t,) for t in texts], "text string").repartition(3))
    total = sum(uses[p] + 1 for p in got)
    assert all(v == pytest.approx(math.log((uses[p] + 1) / total)) for p, v in got.items()) and len(got) > 30000


def test_long_words():
    """A word beyond the kept path has the same count as with all states kept, and the next word is not misled."""
    r = random.Random(4)
    counter = token_counts.Counter({"▁": -2.0, "a": -3.0, "b": -3.5, "ab": -3.2, "aba": -4.0, "▁ab": -2.5})

    def alone(token):
        best = [(0.0, 0)]
        for i in range(len(token)):
            options = [(best[i][0] + counter.fallback, -(best[i][1] + 1))]
            options += [(best[j][0] + counter.vocabulary[token[j : i + 1]], -(best[j][1] + 1)) for j in range(max(0, i - 4), i + 1) if token[j : i + 1] in counter.vocabulary]
            s, n = max(options)
            best.append((s, -n))
        return best[-1][1]

    words = sorted("".join(r.choice("abc" if k % 3 else "ab") for _ in range(n)) for k, n in enumerate([5, 5000, 20000, 30, 1030, 9000])) + ["b" * 6000, "b" * 6001]
    assert counter.count(sorted(words)) == [alone("▁" + w) for w in sorted(words)]


def test_token_counts(docs):
    vocabulary = token_counts.estimate(docs)
    counter = token_counts.Counter(vocabulary)

    def alone(word):
        token = token_counts.MARK + word
        state = [(0.0, 0)]
        for i, c in enumerate(token):
            size = 1 if c == token_counts.MARK else len(c.encode())
            options = [(state[i][0] + counter.fallback * size, -(state[i][1] + size))]
            options += [(state[j][0] + vocabulary[token[j : i + 1]], -(state[j][1] + 1)) for j in range(i + 1) if token[j : i + 1] in vocabulary]
            best = max(options)
            state.append((best[0], -best[1]))
        return state[-1][1]

    want = sorted((i or 0, len(t.encode().split()), sum(alone(w.decode()) for w in t.encode().split())) for i, t in pairs(edge_rows()))
    assert sorted((r["doc_id"] or 0, r["n_pretokens"], r["n_tokens"]) for r in token_counts.token_counts(docs).collect()) == want
    words = sorted(["inter", "internal", "internals", "international"])
    counter.nodes = 0
    counter.count(words)
    assert counter.nodes < sum(len(w) + 1 for w in words)  # prefixes are shared
    assert token_counts.token_counts(docs.limit(0)).count() == 0
