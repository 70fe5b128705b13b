"""What clients get: custom marks, ticks, legends, cards, JSON, formats of user data, linked views."""

import itertools
import json
import random

import numpy as np
import pytest
from conftest import SMALL

from multiscale_scatter.operators import kdtree, kernels, marks
from multiscale_scatter.operators import layout as L
from multiscale_scatter.plans import workloads as W
from multiscale_scatter.plans.materialize import fresh_path
from multiscale_scatter.sources import index as I
from multiscale_scatter.sources.fixtures import CUSTOMER


def test_custom_marks(spark):
    layout = W.lay_out(spark, SMALL, W.PROFILE)
    rows = W.marks_with_payload(layout, W.PROFILE)
    drawn = marks.custom_marks(rows.select("level", "cluster_id", "n", "card"), lambda r: {"cluster_id": r["cluster_id"], "label": f"{json.loads(r['card'])['c_name']} +{r['n'] - 1}"}, "cluster_id long, label string")
    got = {r["label"] for r in drawn.collect()}
    assert len(got) >= rows.where("level = 6").count() and all(" +" in x for x in got)
    assert rows.groupBy("level").sum("n").select("sum(n)").distinct().count() == 1


@pytest.mark.parametrize("name,columns", [("PIES", {"slices", "top", "hull", "sum_l_quantity"}), ("CIRCLE", {"radius", "top", "members_box"}), ("TEXT", {"text"}), ("RADAR", {"axes", "top"}), ("HEATMAP", {"n"})])
def test_payload_of_workloads(spark, name, columns):
    spec = W.smaller(getattr(W, name), 3)
    layout = W.lay_out(spark, SMALL, spec)
    rows = W.marks_with_payload(layout, spec)
    assert columns <= set(rows.columns)
    total = layout.objects.count()
    per = {}
    for r in rows.collect():
        per[r["level"]] = per.get(r["level"], 0) + r["n"]
        if name == "PIES":
            assert sum(r["slices"].values()) == r["n"] and len(r["top"]) == min(3, r["n"]) and r["top"][0] == r["cluster_id"]
        if name == "CIRCLE":
            assert 0 < r["radius"] <= spec.config.max_radius and r["members_box"]["x0"] <= r["x"] <= r["members_box"]["x1"]
        if name == "RADAR":
            assert len(r["axes"]) == 8 and all(0 <= v <= 1 for v in r["axes"])
    assert per == {k: total for k in (1, 2, 3)}


def test_contours_close(spark):
    """Pieces of a contour line meet end to end: every end belongs to two pieces."""
    spec = W.smaller(W.EVENT_CONTOUR, 2)
    pieces = W.contour_lines(W.lay_out(spark, SMALL, spec), spec, 1).collect()
    ends = {}
    for p in pieces:
        for x, y in ((p["x0"], p["y0"]), (p["x1"], p["y1"])):
            key = (p["threshold"], round(x, 5), round(y, 5))
            ends[key] = ends.get(key, 0) + 1
    assert len(pieces) > 20 and set(ends.values()) <= {2, 4}


def test_axes_and_legend():
    plan = L.LayoutPlan((0.0, 10.0), (-5.0, 5.0), levels=3)
    ticks = marks.axis_ticks(plan, 2, 4)
    assert ticks[:2] == [("x", 0.0, 0.0), ("x", 2.5, 500.0)] and ticks[-1] == ("y", 5.0, 2000.0)
    assert marks.legend([100, 25, 100]) == [(25, 12.5), (100, 25.0)]
    tree = kdtree.build(np.array([[float(k), 0.0] for k in range(8)]), 2)
    assert [r[1:3] for r in kdtree.tree_rows(tree)] == [(0, "x"), (1, "x"), (1, "x")]


def test_stored_plan_and_json(spark):
    layout = L.layout_single(CUSTOMER.objects(spark, SMALL), CUSTOMER.plan(levels=2))
    stored = I.write_index(layout, fresh_path(spark, "index"))
    again = I.open_index(spark, I.plan_to_json(stored))
    view = I.Viewport(2, 0.0, 0.0, 900.0, 900.0)
    assert again.plan == stored.plan
    ids = lambda s: sorted(I.ServingSession(s, view).request("x", view, ["cluster_id"]).column("cluster_id").to_pylist())
    assert ids(again) == ids(stored) != []
    first = json.loads(I.payload_json(I.fetch(stored, view)).first()["value"])
    assert {"cluster_id", "cx", "cy", "bbox"} <= set(first)
    picked = marks.compare(layout.objects, [1, 2, 77])
    assert {r["obj_id"] for r in picked.collect()} <= {1, 2, 77}
    linked = I.linked_fetch(stored, picked, 2)
    assert {r["cluster_id"] for r in linked.collect()} <= {1, 2, 77}


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet", "jdbc"])
def test_formats(spark, fmt):
    rows = CUSTOMER.objects(spark, SMALL)
    want = sorted(map(tuple, rows.select("obj_id", "x").collect()))
    path = fresh_path(spark, fmt)
    if fmt == "jdbc":
        url = f"jdbc:derby:memory:{path.rsplit('/', 1)[1]};create=true"
        options = {"url": url, "dbtable": "objects", "driver": "org.apache.derby.iapi.jdbc.AutoloadedDriver"}
        rows.write.format("jdbc").options(**options).save()
        got = I.read_objects(spark, "", "jdbc", **options, partitionColumn="obj_id", lowerBound="1", upperBound="150", numPartitions="3")
        got = got.toDF(*(c.lower() for c in got.columns))
    else:
        options = {"header": "true", "inferSchema": "true"} if fmt == "csv" else {}
        rows.write.options(**({"header": "true"} if fmt == "csv" else {})).format(fmt).save(path)
        got = I.read_objects(spark, path, fmt, **options)
    assert sorted((r["obj_id"], r["x"]) for r in got.select("obj_id", "x").collect()) == [(i, pytest.approx(x)) for i, x in want]


def test_greedy_against_the_optimum():
    """Few objects, all sets of marks: greedy takes the most important object, keeps the distance, and can't be added to;
    the best set by total importance is at least as good."""
    r = random.Random(6)
    for _ in range(40):
        n = r.randrange(2, 10)
        u, v = np.array([r.random() * 4 for _ in range(n)]), np.array([r.random() * 4 for _ in range(n)])
        z = sorted((r.random() for _ in range(n)), reverse=True)
        gap = lambda a, b: max(abs(u[a] - u[b]), abs(v[a] - v[b]))  # noqa: E731, B023
        apart = [s for k in range(1, n + 1) for s in itertools.combinations(range(n), k) if all(gap(a, b) >= 1 for a, b in itertools.combinations(s, 2))]
        into = kernels.place_with_grid(u, v, 1.0)
        mine = tuple(k for k in range(n) if into[k] == k)
        assert mine in apart and 0 in mine and not any(set(mine) < set(s) for s in apart)
        assert sum(z[k] for k in mine) <= max(sum(z[k] for k in s) for s in apart) + 1e-12
        assert mine == max(apart, key=lambda s: [k in s for k in range(n)])  # the best set in order of importance


def test_session_keeps_few_files_open(spark, tmp_path, monkeypatch):
    """An index of more files than a process may open: footers are read and closed, the files asked for last stay open."""
    import os

    from multiscale_scatter.sources import index as I

    monkeypatch.setattr(I, "OPEN_FILES", 3)
    path = str(tmp_path / "index")
    rows = spark.range(400).selectExpr("id AS cluster_id", "CAST(id AS DOUBLE) AS cx", "CAST(id AS DOUBLE) AS cy", "1 AS level")
    rows.repartitionByRange(20, "cx").write.partitionBy("level").parquet(path)
    before = len(os.listdir("/proc/self/fd"))
    groups = I.RowGroups(path)
    for x in (0.0, 100.0, 250.0, 0.0):
        items, _ = groups.fetch(I.Viewport(1, x, x, x + 149, x + 149), 0.0, 0.0)
        assert sorted(items.column("cluster_id").to_pylist()) == list(range(int(x), int(x) + 150))
        assert len(os.listdir("/proc/self/fd")) <= before + 3
