"""Ways for sizes that tests don't have: exact trees, crowded places, rounds, many children, row groups."""

import random

import numpy as np
import pytest
from conftest import MIDDLE, SMALL
from pyspark.sql import functions as F

from multiscale_scatter.operators import kdtree, kernels, measures, rollup
from multiscale_scatter.operators import layout as L
from multiscale_scatter.plans import materialize as M
from multiscale_scatter.queries import registry
from multiscale_scatter.queries.layout_queries import kd_sql
from multiscale_scatter.sources.fixtures import CUSTOMER, LINEITEM, SUPPLIER


@pytest.mark.parametrize("fixture,most", [(CUSTOMER, 90), (LINEITEM, 1500)])
def test_exact_tree(spark, fixture, most):
    """The tree of all rows by jobs is the tree of all rows in memory; ties of either axis included."""
    rows = fixture.objects(spark, MIDDLE)
    points = np.array([(r["x"], r["y"]) for r in rows.select("x", "y").collect()])
    want, got = kdtree.build(points, most), kdtree.build_exact(rows, most)
    shape = lambda t: [(s.depth, s.axis, s.value, s.first, s.middle, s.end) for s in sorted(t.splits, key=lambda s: (s.depth, s.first))]
    assert shape(got) == shape(want) and got.leaves == want.leaves > 10
    same = spark.createDataFrame([(1.0, 2.0)] * 9, "x double, y double")
    assert kdtree.build_exact(same, 3).leaves == 1 and kdtree.build_exact(same.limit(0), 3).leaves == 1


def plain_distributed(objects, plan, tree):
    """Edges of a layout by leaves, then splits, in plain Python, row by row."""
    ids = sorted(objects, key=lambda i: (-objects[i][2], i))
    rank = {i: k for k, i in enumerate(ids)}
    (x0, x1), (y0, y1) = plan.x_extent, plan.y_extent
    leaf = {i: int(tree.leaf_of(np.array([objects[i][0]]), np.array([objects[i][1]]))[0]) for i in ids}
    live, out = ids, []
    for level in range(plan.levels, 0, -1):
        size = [s * plan.zoom ** (level - 1) / b for s, b in zip(plan.top, plan.box)]
        unit = lambda v, lo, hi, k: (v - lo) / (hi - lo) * (plan.top[k] * plan.zoom ** (plan.levels - 1)) / plan.box[k] * plan.zoom ** (level - plan.levels)  # noqa: E731, B023
        at = {i: (unit(objects[i][0], x0, x1, 0), unit(objects[i][1], y0, y1, 1)) for i in live}
        gap = lambda a, b: max(abs(at[a][0] - at[b][0]), abs(at[a][1] - at[b][1]))  # noqa: E731, B023
        into, stands = {}, []
        for i in live:
            near = [(gap(i, s), rank[s], s) for s in stands if leaf[s] == leaf[i] and gap(i, s) < plan.theta]
            into[i] = min(near)[2] if near else i
            if not near:
                stands.append(i)
        for split in sorted(tree.splits, key=lambda s: (-s.depth, s.first)):
            ends = ((x0, x1), (y0, y1))[split.axis]
            line = (split.value - ends[0]) / (ends[1] - ends[0]) * size[split.axis]
            band = [i for i in stands if split.first <= leaf[i] < split.end and abs(at[i][split.axis] - line) < plan.theta]
            last = None
            for i in sorted(band, key=lambda i: (at[i][1 - split.axis], rank[i])):
                if last is None or gap(i, last) >= plan.theta:
                    last = i
                    continue
                lose, win = (last, i) if rank[i] < rank[last] else (i, last)
                for k in [k for k, v in into.items() if v == lose]:
                    into[k] = win
                stands.remove(lose)
                last = win
        out += [(level, c, p) for c, p in into.items()]
        live = [i for i in live if into[i] == i]
    return sorted(out)


@pytest.mark.parametrize("fixture,cap,depth", [(SUPPLIER, 8, 8), (SUPPLIER, 20, 1), (CUSTOMER, 30, 2)])
def test_distributed_edge_by_edge(spark, fixture, cap, depth):
    folder = MIDDLE if fixture is SUPPLIER else SMALL
    plan = fixture.plan(mem_cap=cap)
    layout = L.layout_distributed(fixture.objects(spark, folder), plan, hybrid=False, supernode_depth=depth)
    objects = {r["obj_id"]: (r["x"], r["y"], r["z"]) for r in layout.objects.collect()}
    assert layout.tree.leaves >= 4
    assert sorted(map(tuple, layout.edges.collect())) == plain_distributed(objects, plan, layout.tree)


def test_crowded_place(spark):
    """More objects at one place than a task holds: their copies follow the most important one."""
    r = random.Random(1)
    rows = [(k, 5.0, 5.0, float(k % 50)) for k in range(400)] + [(1000 + k, r.random() * 10, r.random() * 10, r.random()) for k in range(200)]
    objects = spark.createDataFrame(rows, "obj_id long, x double, y double, z double")
    plan = L.LayoutPlan((0.0, 10.0), (0.0, 10.0), levels=3, mem_cap=40)
    for hybrid in (True, False):
        layout = L.layout_distributed(objects, plan, hybrid=hybrid)
        assert layout.edges.where("level = 3").count() == 600 == layout.members(1).count()
        assert measures.overlap_violations(layout.marks(), *plan.box, plan.theta).agg(F.sum("violations")).first()[0] == 0
        assert {row["objects"] for row in measures.mass_conservation(rollup.all_levels(layout)).collect()} == {600}
        assert layout.edges.where("level = 3 and child < 400").select("parent").distinct().count() == 1


def test_many_children(spark, monkeypatch):
    """Hulls and top lists of a parent with many children, gathered a few at a time."""
    monkeypatch.setattr(rollup, "GATHERED", 7)
    r = random.Random(2)
    rows = [(k, r.random(), r.random(), float(r.randrange(30))) for k in range(300)]
    objects = spark.createDataFrame(rows, "obj_id long, x double, y double, z double")
    plan = L.LayoutPlan((0.0, 1.0), (0.0, 1.0), levels=1, box=(3000.0, 3000.0))
    state = rollup.all_levels(L.layout_single(objects, plan), k=5, hull=True).first()
    best = sorted(rows, key=lambda x: (-x[3], x[0]))[:5]
    assert [t["obj_id"] for t in state["topk"]] == [x[0] for x in best]
    want = kernels.convex_hull(np.array([(x[1], x[2]) for x in rows]))
    assert {(p["x"], p["y"]) for p in state["hull"]} == set(map(tuple, want.tolist())) and state["n"] == 300


def test_percent_ranks(spark):
    rows = [(k, z) for k, z in enumerate([3.0, 1.0, 1.0, None, 7.0, 7.0, 7.0, -2.0])]
    got = {r["cluster_id"]: r["p"] for r in measures.percent_ranks(spark.createDataFrame(rows, "obj_id long, z double")).collect()}
    below = lambda z: sum((y is None and z is not None) or (y is not None and z is not None and y < z) for _, y in rows)
    assert got == {k: pytest.approx(below(z) / 7) for k, z in rows}


def test_tables(spark, monkeypatch):
    import os

    with M.scratch(spark):
        inner = M.materialize(spark.range(5), "inner")
        outer = M.materialize(inner, "outer", outside=True)
    assert outer.count() == 5 and not os.path.exists(inner._table_path)
    M.discard(outer, None, spark.range(3))
    assert not os.path.exists(outer._table_path)

    class Away:
        master = "spark://far:7077"

    class Session:
        sparkContext = Away()
        conf = {"none": "none"}

    with pytest.raises(RuntimeError):
        M.shared_folder(Session())


def test_pairs_are_counted_by_places(spark):
    """Violations and isolated objects against all pairs, with copies of places; no side of a join goes to the driver."""
    rng = random.Random(5)
    spots = [(rng.uniform(0, 3000), rng.uniform(0, 3000)) for _ in range(150)] + [(100.0, 100.0), (200.0, 100.0), (199.5, 100.0)]
    rows = [(1 + i % 2, i, *spots[rng.randrange(150) if i > 200 else i % len(spots)]) for i in range(400)]
    marks = spark.createDataFrame(rows, "level int, cluster_id long, cx double, cy double")
    gap = lambda p, q: max(abs(p[2] - q[2]) / 100, abs(p[3] - q[3]) / 50)
    close = [(p, q) for p in rows for q in rows if p[0] == q[0] and p[1] < q[1]]
    got = measures.overlap_violations(marks, 100.0, 50.0, 1.0)
    assert {r["level"]: r["violations"] for r in got.collect()} == {k: sum(p[0] == k and gap(p, q) < 1 - 1e-9 for p, q in close) for k in (1, 2)}
    busy = {i for p, q in close if gap(p, q) < 1 for i in (p[1], q[1])}
    alone = measures.isolated(marks, 100.0, 50.0, 1.0)
    assert {r["cluster_id"] for r in alone.collect()} == {r[1] for r in rows} - busy
    for df in (got, alone, measures.close_pairs(marks, 100.0, 50.0, 1.0)):
        assert "BroadcastExchange" not in df._jdf.queryExecution().executedPlan().toString()


def test_chains_take_few_rounds(spark):
    """A row of objects, each blocked by the next more important one, takes a round a tile, not one an object."""
    plan = L.LayoutPlan((0.0, 1.0), (0.0, 1.0), levels=6)
    rows = spark.range(1400).selectExpr("id AS obj_id", "(id DIV 2) * 60.0D / 42000 AS x", "0.5D AS y", "CAST(-id AS DOUBLE) AS z")
    triple = lambda lay: sorted(map(tuple, lay.edges.select("level", "child", "parent").collect()))
    assert triple(L.layout_rounds(rows, plan, max_rounds=12)) == triple(L.layout_single(rows, plan))


def test_small_tiles(spark, monkeypatch):
    """The same marks with tiles of a few cells and tasks of a few rows."""
    monkeypatch.setattr(L, "TILE", 3)
    monkeypatch.setattr(L, "TILE_ROWS", 40)
    plan = SUPPLIER.plan(levels=3)
    triple = lambda lay: sorted(map(tuple, lay.edges.select("level", "child", "parent").collect()))
    rows = SUPPLIER.objects(spark, MIDDLE)
    assert triple(L.layout_rounds(rows, plan)) == triple(L.layout_single(rows, plan))


def test_what_fits_a_task_is_one_tile(spark, monkeypatch):
    """Levels of no more rows than a task takes need no rounds."""
    rounds = []
    monkeypatch.setattr(L, "materialize", lambda df, name, keep=L.materialize: (name == "chosen" and rounds.append(name), keep(df, name))[1])
    plan = SUPPLIER.plan(levels=3)
    triple = lambda lay: sorted(map(tuple, lay.edges.select("level", "child", "parent").collect()))
    rows = SUPPLIER.objects(spark, MIDDLE)
    assert triple(L.layout_rounds(rows, plan)) == triple(L.layout_single(rows, plan)) and not rounds
    one = L.layout_top_down(rows, plan).visible().collect()
    assert not rounds
    monkeypatch.setattr(L, "TILE_ROWS", 40)
    assert sorted(map(tuple, L.layout_top_down(rows, plan).visible().collect())) == sorted(map(tuple, one)) and rounds


def test_top_down_of_copies(spark):
    """Copies of a place never stand beside its first object, on no level; nothing goes to the driver for them."""
    plan = CUSTOMER.plan(levels=3)
    rows = CUSTOMER.objects(spark, SMALL)
    more = rows.unionByName(rows.withColumn("obj_id", F.col("obj_id") + 1_000_000))
    marks = lambda lay: sorted(map(tuple, lay.visible().collect()))
    assert marks(L.layout_top_down(more, plan, max_rounds=4)) == marks(L.layout_top_down(rows, plan))


def _copied(tmp_path, table, times, more):
    """A folder with SMALL's table several times, keys shifted, and some rows of one more copy, and a DuckDB view of it."""
    import duckdb

    con = duckdb.connect()
    key = {"events": "event_id", "lineitem": "l_orderkey"}[table]
    src = f"'{SMALL}/{table}.parquet'"
    rows = f"SELECT * REPLACE ({key} + i * 1000000 AS {key}) FROM {src}, range(0, {times}) AS t(i)"
    con.execute(f"COPY (SELECT * EXCLUDE i FROM ({rows}) UNION ALL (SELECT * REPLACE ({key} + 90000000 AS {key}) FROM {src} ORDER BY {key} LIMIT {more})) TO '{tmp_path}/{table}.parquet' (FORMAT parquet)")
    con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{tmp_path}/{table}.parquet'")
    return con


@pytest.mark.parametrize("name,more", [("kd_leaf_counts", 0), ("kd_prune", 5), ("stream_kd_assign", 0)])
def test_trees_with_ties(spark, tmp_path, name, more):
    """Copies at the medians make sides of unequal size; a tree of so many medians has no more leaves for that."""
    con = _copied(tmp_path, "events", 7, more)
    want = sorted(con.sql(registry.ORACLES[name]).fetchall())
    assert sorted(map(tuple, registry.QUERIES[name](spark, str(tmp_path)).collect())) == want


def test_tree_of_some_turns(spark, tmp_path):
    con = _copied(tmp_path, "lineitem", 3, 0)
    tree = kdtree.build_exact(LINEITEM.objects(spark, str(tmp_path)), 50, turns=7)
    got = measures.partition_skew(L.assign_leaf(LINEITEM.objects(spark, str(tmp_path)), tree)).select("leaves", "largest").first()
    assert tuple(got) == con.sql(kd_sql(LINEITEM, 50, 7)).fetchall()[0]
    assert got["largest"] > 50


def test_complete_results_stay_off_the_driver(spark):
    """No complete result is held by the driver's memory sink."""
    before = {t.name for t in spark.catalog.listTables()}
    assert registry.QUERIES["stream_session"](spark, SMALL).inputFiles()
    assert not {t.name for t in spark.catalog.listTables() if t.name.startswith("sink")} - before


def test_objects_that_share_an_id(spark, tmp_path):
    """Two lines of one order, number and price but other quantities: all of them are counted, the id has one mark."""
    import os

    import duckdb

    for f in os.listdir(SMALL):
        if f != "lineitem.parquet":
            os.symlink(f"{SMALL}/{f}", tmp_path / f)
    con = duckdb.connect()
    src = f"'{SMALL}/lineitem.parquet'"
    con.execute(f"COPY (SELECT * FROM {src} UNION ALL SELECT * REPLACE (l_quantity % 50 + 1 AS l_quantity) FROM {src} WHERE l_orderkey < 30) TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet'")
    want = sorted(con.sql(registry.ORACLES["wl_pie_mass"]).fetchall())
    assert want[0][1] > 6000
    assert sorted(map(tuple, registry.QUERIES["wl_pie_mass"](spark, str(tmp_path)).collect())) == want
    layout = L.layout_distributed(LINEITEM.objects(spark, str(tmp_path)), LINEITEM.plan(mem_cap=500), hybrid=False)
    assert {r["objects"] for r in measures.mass_conservation(rollup.all_levels(layout)).collect()} == {want[0][1]}
    marks = layout.marks()
    assert layout.shared_ids and marks.count() == marks.select("level", "cluster_id").distinct().count() == layout.visible().count()


def test_ranks_are_shared(spark, monkeypatch):
    """The six layouts are of the same objects, whose ranks are made once; each one's measures are those it has alone."""
    calls = []
    monkeypatch.setattr(measures, "percent_ranks", lambda objects, keep=measures.percent_ranks: (calls.append(1), keep(objects))[1])
    got = registry.QUERIES["layout_mark_counts"](spark, SMALL).where("layout = 'single'").drop("layout").toPandas().sort_values("level")
    assert len(calls) == 1
    alone = measures.quality(L.layout_single(CUSTOMER.objects(spark, SMALL), CUSTOMER.plan(mem_cap=400))).toPandas().sort_values("level")
    assert len(got) == 6 and np.allclose(got.to_numpy(float), alone.to_numpy(float), atol=1e-9)
