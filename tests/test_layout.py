import pytest
from conftest import MIDDLE, SMALL
from pyspark.sql import functions as F

from multiscale_scatter.operators import layout as L
from multiscale_scatter.operators import measures
from multiscale_scatter.operators.rollup import all_levels, hover_details, value_of
from multiscale_scatter.plans.materialize import fresh_path
from multiscale_scatter.sources import index as I
from multiscale_scatter.sources.fixtures import CUSTOMER, EVENTS, SUPPLIER

EV = EVENTS.plan(mem_cap=300)


def counts(layout):
    return [n for _, n in sorted(L.visible_iterator(layout), reverse=True)]


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_known_marks(spark):
    plan = EVENTS.plan().with_(y_extent=(0.0, 500.0))
    objects = EVENTS.objects(spark, MIDDLE)
    assert counts(L.layout_single(objects, plan)) == [5729, 2835, 1120, 397, 133, 42]
    distributed = L.layout_distributed(objects, plan.with_(mem_cap=500), hybrid=False)
    assert counts(distributed) == [5691, 2772, 1068, 353, 107, 28] and distributed.tree.leaves == 32
    shallow = L.layout_distributed(objects, plan.with_(mem_cap=500), hybrid=False, supernode_depth=2)
    assert rows(measures.overlap_violations(shallow.marks(), *plan.box, plan.theta)) == [(k, 0) for k in range(1, 7)]


def test_rounds_equal_one_task(spark):
    objects = SUPPLIER.objects(spark, MIDDLE)
    assert rows(L.layout_rounds(objects, SUPPLIER.plan()).edges) == rows(L.layout_single(objects, SUPPLIER.plan()).edges)


def test_negative_controls(spark):
    objects = EVENTS.objects(spark, SMALL)
    plan = EV.with_(levels=2, mem_cap=100, box=(400.0, 400.0))
    total = lambda lay: measures.overlap_violations(lay.marks(), *plan.box, plan.theta).agg(F.sum("violations")).first()[0]
    assert total(L.layout_distributed(objects, plan, hybrid=False)) == 0
    assert total(L.layout_distributed(objects, plan, hybrid=False, repair=False)) > 0
    assert total(L.layout_hash_partition(objects, plan, 4)) > 0


@pytest.mark.parametrize("kind", ["single", "distributed"])
def test_invariants(spark, kind):
    objects = EVENTS.objects(spark, SMALL)
    lay = L.layout_single(objects, EV) if kind == "single" else L.layout_distributed(objects, EV, hybrid=False)
    assert measures.zoom_violations(lay.visible(), 6).count() == 0
    states = all_levels(lay, measures={"v": "y"}, k=3, hull=True)
    total = objects.count()
    assert {tuple(r) for r in measures.mass_conservation(states).select("level", "objects").collect()} == {(k, total) for k in range(1, 7)}
    sums = states.groupBy("level").agg(F.round(F.sum(value_of("v", "sum")), 3).alias("s")).select("s").distinct().collect()
    assert len(sums) == 1
    # the first of a top list is the representative; merged states equal those of walked members
    assert states.where("topk[0].obj_id <> cluster_id").count() == 0
    walked = lay.members(2).join(objects, "obj_id").groupBy("cluster_id").agg(F.count("*").alias("n"), F.max("y").alias("m"))
    merged = states.where("level = 2").select("cluster_id", "n", F.col("v_max").alias("m"))
    assert rows(walked) == rows(merged)
    assert hover_details(lay, states.where("level = 1")).where("place > 3").count() == 0
    most = measures.viewport_density(lay.marks(3), 1000.0, 1000.0).first()["most"]
    assert most <= 100


def test_bad_places_and_theta_zero(spark):
    data = [(1, 0.0, 0.0, 1.0), (2, None, 0.0, 2.0), (3, float("nan"), 1.0, 3.0), (4, 5.0, 5.0, None), (5, 99.0, 0.0, 1.0), (6, 10.0, 10.0, 0.0)]
    objects = spark.createDataFrame(data, "obj_id long, x double, y double, z double")
    plan = L.LayoutPlan((0.0, 10.0), (0.0, 10.0), levels=2)
    assert {r["child"] for r in L.layout_single(objects, plan).edges.collect()} == {1, 4, 6}
    nothing = L.layout_single(objects, plan.with_(theta=0.0))
    assert nothing.edges.where("child <> parent").count() == 0
    empty = L.layout_single(objects.limit(0), plan)
    assert empty.edges.count() == 0
    assert L.layout_distributed(objects.limit(0), plan).edges.count() == 0


def test_index_and_serving(spark):
    lay = L.layout_distributed(EVENTS.objects(spark, MIDDLE), EVENTS.plan(mem_cap=500), hybrid=False)
    stored = I.write_index(lay, fresh_path(spark, "index"))
    for view in (I.Viewport(6, 3000.0, 100.0, 5000.0, 1500.0), I.Viewport(1, 0.0, 0.0, 1000.0, 1000.0), I.Viewport(5, 7950.0, 450.0, 8050.0, 550.0)):
        full = rows(I.fetch(stored, view, pruned=False, pushdown=False).select("cluster_id"))
        assert rows(I.fetch(stored, view).select("cluster_id")) == full
        assert rows(I.fetch(stored, view, pruned=False).select("cluster_id")) == full
    plan = I.fetch(stored, view)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters" in plan and "GreaterThanOrEqual(cx" in plan
    one, two = (I.ServingSession(stored, view, engine=e) for e in ("groups", "spark"))
    for k in range(1, 7):
        for box in ((0.0, 0.0, 1000.0, 1000.0), (250.0, 90.0, 700.0, 480.0), (-50.0, -50.0, 0.0, 0.0), (9e5, 0.0, 1e6, 10.0)):
            got = [s.request("x", I.Viewport(k, *box), ["cluster_id", "cx", "cy"]) for s in (one, two)]
            assert sorted(got[0].to_pylist(), key=str) == sorted(got[1].to_pylist(), key=str)
    assert one.samples[0]["items"] == two.samples[0]["items"] > 0 and one.samples[0]["bytes"] > 0
    report = I.latency_report(one.samples)
    assert report["requests"] == 24 and report["bytes_p95"] > 0
    bands = {}
    for r in L.band_sizes(lay).collect():
        bands[r["level"], r["depth"]] = bands.get((r["level"], r["depth"]), 0) + r["rows"]
    first = lay.tree.splits[0]
    lo, hi = lay.plan.x_extent
    xs = [r["x"] for r in lay.objects.select("x").collect()]
    assert bands[6, 0] == sum(abs(x - first.value) / (hi - lo) * 320.0 < 1 for x in xs)
    assert set(lay.phases) == {"tree", "redistribution", "clustering", "boundary", "top"} and lay.phases["boundary"] > 0
    seen = []
    session = I.ServingSession(stored, I.Viewport(1, 0.0, 0.0, 1000.0, 1000.0), listeners=[lambda a, v: seen.append(a)])
    session.zoom(1)
    session.pan(100.0, 0.0)
    session.jump(3, 500.0, 500.0)
    assert seen == ["zoom_in", "pan", "jump"] and session.view.level == 3
    old, new = I.Viewport(6, 0.0, 0.0, 1000.0, 1000.0), I.Viewport(6, 300.0, 0.0, 1300.0, 1000.0)
    delta = rows(I.pan_delta(stored, old, new).select("cluster_id"))
    assert set(delta) == set(rows(I.fetch(stored, new).select("cluster_id"))) - set(rows(I.fetch(stored, old).select("cluster_id")))
    trace = I.generate_trace(stored, 1000.0, 1000.0)
    assert [v.level for _, v in trace][-1] == 1 and max(v.level for _, v in trace) == 6
    assert I.nearest_rank([1.0, 2.0, 3.0, 4.0], 0.5) == 2.0 and I.nearest_rank(list(range(1, 101))) == 95


def test_relayout(spark):
    objects = CUSTOMER.objects(spark, SMALL)
    old = L.layout_distributed(objects.where("obj_id % 2 = 0"), CUSTOMER.plan(mem_cap=40), hybrid=False)
    new = L.relayout(old, objects.where("obj_id % 2 = 1"))
    assert new.objects.count() == objects.count()
