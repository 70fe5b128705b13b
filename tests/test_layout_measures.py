"""Measures of the marks of a layout, all levels of the whole table, against brute force."""

from collections import defaultdict

from conftest import SMALL

from multiscale_scatter.queries import registry
from multiscale_scatter.queries import stats_queries as S


def run(spark, name):
    return registry.QUERIES[name](spark, SMALL).collect()


def test_measures_of_layout_marks(spark):
    layout = S._laid_out(spark, SMALL, S.ORDERS)
    objects = {r["obj_id"]: r["z"] for r in layout.objects.select("obj_id", "z").collect()}
    at = defaultdict(dict)
    for r in layout.marks().collect():
        at[r["level"]][r["cluster_id"]] = (r["cx"], r["cy"])
    levels = range(1, layout.plan.levels + 1)
    assert len(objects) > 1000 and set(at) == set(levels)
    w, h = (s * layout.plan.theta for s in layout.plan.box)
    full = {r["level"]: r for r in run(spark, "layout_fullness")}
    for i in levels:
        size = 1000.0 * 2 ** (i - 1)
        capacity = (int(size // w) + 1) * (int(size // h) + 1)
        cells = {(x // w, y // h) for x, y in at[i].values()}
        assert full[i]["marks"] == len(at[i]) and abs(full[i]["share"] - len(at[i]) / capacity) < 1e-12 and abs(full[i]["occupied"] - len(cells) / capacity) < 1e-12
    below = defaultdict(int)
    for v in objects.values():
        below[v] += 1
    ranks, n = {}, 0
    for v in sorted(below):
        ranks[v] = n / (len(objects) - 1)
        n += below[v]
    top = [o for o, z in objects.items() if ranks[z] >= 0.9]
    for r in run(spark, "layout_importance"):
        seen = at[r["level"]]
        assert abs(r["mean_rank"] - sum(ranks[objects[o]] for o in seen) / len(seen)) < 1e-9
        assert abs(r["top_visible"] - sum(o in seen for o in top) / len(top)) < 1e-9
    gone = sorted((i, o) for i in levels[:-1] for o in at[i] if o not in at[i + 1])
    assert sorted(map(tuple, run(spark, "layout_zoom_consistency"))) == gone
    first = min((i for i in levels if 64 in at[i]), default=None)
    assert [tuple(r) for r in run(spark, "layout_object_level")] == [(64, first)]
    top_level = list(at[1].values())
    close = sum(abs(a[0] - b[0]) < w * (1 - 1e-9) and abs(a[1] - b[1]) < h * (1 - 1e-9) for k, a in enumerate(top_level) for b in top_level[:k])
    got = {r["level"]: r["violations"] for r in run(spark, "layout_overlap")}
    assert set(got) == set(levels) and got[1] == close


def test_density_of_layout_marks(spark):
    at = defaultdict(list)
    for r in S._laid_out(spark, SMALL, S.SUPPLIER).marks().collect():
        at[r["level"]].append((r["cx"], r["cy"]))
    most = {i: max(sum(x <= a < x + 1000 and y <= b < y + 1000 for a, b in p) for x, _ in p for _, y in p) for i, p in at.items()}
    assert {r["level"]: r["most"] for r in run(spark, "layout_viewport_density")} == most


def test_variation_of_every_level(spark):
    out = {r["level"]: r["variation"] for r in run(spark, "layout_variation")}
    layout = S._laid_out(spark, SMALL, S.ORDERS)
    places = {r["obj_id"]: (r["x"], r["y"]) for r in layout.objects.collect()}
    (x0, x1), (y0, y1) = layout.plan.x_extent, layout.plan.y_extent
    assert set(out) == set(range(1, layout.plan.levels + 1))
    for level in (1, 4):
        size = 1000.0 * 2 ** (level - 1)
        gaps = []
        for r in layout.members(level).collect():
            (ax, ay), (bx, by) = places[r["obj_id"]], places[r["cluster_id"]]
            gaps.append((((ax - bx) / (x1 - x0) * size) ** 2 + ((ay - by) / (y1 - y0) * size) ** 2) ** 0.5)
        assert abs(out[level] - sum(gaps) / len(gaps)) < 1e-6
