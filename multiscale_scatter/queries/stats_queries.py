"""Cluster statistics, payloads, measures and baselines, on clusters that SQL can form too.

Clusters that SQL can form are the cells of a grid, as a layout of one level; marks that it can place are those
of a one-task layout of a small table, all levels of it.  The queries layout_* measure the marks of distributed
layouts; SQL has no such marks, so tests hold them against brute force.  The nested sample by id (on level i the
objects whose id is a multiple of 4^(6 - i)) is the sampling baseline.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators import baselines, kde, marks, measures
from ..operators import layout as L
from ..operators.rollup import all_levels, hull_area, hull_area_of, value_of, variance_of
from ..operators.rollup import hover_details as object_details
from ..sources.fixtures import CUSTOMER, EVENTS, LINEITEM, ORDERS, PIE, SUPPLIER, table
from ..sources.index import nearest_rank_of
from .layout_queries import greedy_sql

LEVELS = 6


def _sampled(spark, d, fixture, *more):
    """level, cluster_id, cx, cy of the nested sample, on each level's own canvas."""
    rows = baselines.sample_levels(fixture.pixels(spark, d, LEVELS, *more), LEVELS)
    scale = F.pow(F.lit(2.0), F.col("level") - LEVELS)
    return rows.withColumns({"cx": F.col("cx") * scale, "cy": F.col("cy") * scale}).withColumn("cluster_id", F.col("obj_id"))


def _sampled_sql(fixture, *more):
    return (
        f"(SELECT l.level, obj_id AS cluster_id, x, y, z, cx * pow(2.0, l.level - 6) AS cx, cy * pow(2.0, l.level - 6) AS cy{''.join(', ' + m.split(' AS ')[-1] for m in more)} "
        f"FROM {fixture.pixels_sql(LEVELS, *more)}, range(1, 7) AS l(level) WHERE obj_id % CAST(pow(4.0, 6 - l.level) AS BIGINT) = 0)"
    )


def _binned(spark, d, fixture, *more, width=250.0):
    rows = fixture.pixels(spark, d, 1, *more)
    return rows.withColumn("cell", (F.floor(F.col("cx") / width) + 100 * F.floor(F.col("cy") / width)).cast("long"))


def _binned_sql(fixture, *more, width=250.0):
    return f"(SELECT *, CAST(floor(cx / {width}) + 100 * floor(cy / {width}) AS BIGINT) AS cell FROM {fixture.pixels_sql(1, *more)})"


def _cells(spark, d, fixture, *more, width=250.0, pixels=False):
    """(layout, cells): the grid's cells as clusters of a layout of one level; cells(cluster_id, cell)."""
    rows = _binned(spark, d, fixture, *more, width=width)
    rep = rows.groupBy("cell").agg(F.min(F.struct((-F.col("z")).alias("w"), F.col("obj_id").alias("id"))).alias("m")).select("cell", F.col("m.id").alias("cluster_id"))
    edges = rows.join(rep, "cell").select(F.lit(1).alias("level"), F.col("obj_id").alias("child"), F.col("cluster_id").alias("parent"))
    objects = rows.drop("cell")
    if pixels:
        objects = objects.withColumns({"x": F.col("cx"), "y": F.col("cy")})
    return L.Layout(fixture.plan(levels=1), objects, edges), rep


def _cell_states(spark, d, fixture, *more, width=250.0, pixels=False, **options):
    layout, cells = _cells(spark, d, fixture, *more, width=width, pixels=pixels)
    return all_levels(layout, **options).join(cells, "cluster_id")


def agg_measures(spark, d):
    out = _cell_states(spark, d, EVENTS, measures={"v": "z"})
    value = lambda f, n: F.round(value_of("v", f), n)
    return out.select("cell", F.col("v_cnt").alias("n"), value("sum", 4).alias("total"), value("avg", 6).alias("mean"), value_of("v", "min").alias("least"), value_of("v", "max").alias("most"), value("sqrsum", 2).alias("squares"))


def agg_by_dimension(spark, d):
    out = _cell_states(spark, d, EVENTS, "event_type", measures={"v": "z"}, dimensions=["event_type"])
    return out.select("cell", "event_type", "n", F.round("v_sum", 4).alias("total"))


def hover_topk(spark, d):
    rows = _cell_states(spark, d, EVENTS, k=3)
    return rows.select("cell", F.posexplode("topk").alias("place", "e")).select("cell", (F.col("place") + 1).alias("place"), F.col("e.obj_id").alias("obj_id"))


def hover_bbox(spark, d):
    return _cell_states(spark, d, EVENTS).select("cell", *(F.round(c, 6).alias(c) for c in ("x0", "y0", "x1", "y1")))


def hover_details(spark, d):
    layout, cells = _cells(spark, d, EVENTS, "user_id", "event_type", "value")
    details = object_details(layout, all_levels(layout, k=3)).where("place = 1")
    return details.join(cells, "cluster_id").select("cell", "obj_id", "user_id", "event_type", "value")


def hull_area_cells(spark, d):
    return _cell_states(spark, d, CUSTOMER, width=500.0, pixels=True, hull=True).select("cell", F.round(hull_area("hull"), 4).alias("area"))


def hull_area_udaf(spark, d):
    """The same areas by an aggregate function over a cell's points."""
    return _binned(spark, d, SUPPLIER, width=500.0).groupBy("cell").agg(F.round(hull_area_of("cx", "cy"), 4).alias("area"))


def hull_corners(spark, d):
    """Corners of the hulls: points that some line through them leaves all others on one side of."""
    rows = _cell_states(spark, d, CUSTOMER, width=500.0, pixels=True, hull=True)
    return rows.select("cell", F.explode("hull").alias("c")).select("cell", F.round("c.x", 6).alias("x"), F.round("c.y", 6).alias("y"))


def agg_derived_var(spark, d):
    return _cell_states(spark, d, EVENTS, measures={"v": "z"}).select("cell", F.round(variance_of("v"), 4).alias("variance"))


def rep_by_struct(spark, d):
    return _cell_states(spark, d, EVENTS, k=1).select("cell", F.col("topk")[0]["obj_id"].alias("rep"))


def _single(spark, d, fixture):
    return L.layout_single(fixture.objects(spark, d), fixture.plan())


def overlap_violations(spark, d):
    layout = _single(spark, d, CUSTOMER)
    return measures.overlap_violations(layout.marks(), *layout.plan.box, layout.plan.theta)


def overlap_of_sample(spark, d):
    """The sampling baseline for comparison: its marks do overlap."""
    return measures.overlap_violations(_sampled(spark, d, ORDERS), 100.0, 100.0, 1.0)


def viewport_density(spark, d):
    return measures.viewport_density(_single(spark, d, SUPPLIER).marks(), 1000.0, 1000.0)


def zoom_consistency(spark, d):
    layout = _single(spark, d, CUSTOMER)
    return measures.zoom_violations(layout.visible(), layout.plan.levels)


def fullness(spark, d):
    layout = _single(spark, d, CUSTOMER)
    out = measures.fullness(layout.marks(), layout.plan)
    return out.select("level", "marks", F.col("capacity").cast("long").alias("capacity"), F.round("share", 9).alias("share"), F.round("occupied", 9).alias("occupied"))


def importance_by_level(spark, d):
    layout = _single(spark, d, CUSTOMER)
    out = measures.importance_by_level(layout.visible(), layout.objects)
    return out.select("level", F.round("mean_rank", 6).alias("mean_rank"), F.round("top_visible", 6).alias("top_visible"))


def within_cluster_variation(spark, d):
    """Mean distance of objects from the mark that stands for them, on every level."""
    layout = _single(spark, d, CUSTOMER)
    parts = [measures.within_cluster_variation(layout, level) for level in range(1, layout.plan.levels + 1)]
    return reduce(lambda a, b: a.unionByName(b), parts).select("level", F.round("variation", 6).alias("variation"))


def mass_conservation(spark, d):
    states = _cell_states(spark, d, EVENTS, measures={"v": "z"})
    total = states.agg(F.round(F.sum("v_sum"), 3).alias("total"))
    return measures.mass_conservation(states).select("objects").crossJoin(F.broadcast(total))


def p95_nearest_rank(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(nearest_rank_of("value").alias("p95"))


def provisioning(spark, d):
    """What a layout of each quantity's line items takes, at 100 objects a partition and 8 partitions a node."""
    sizes = table(spark, d, "lineitem").groupBy("l_quantity").agg(F.count(F.lit(1)).alias("objects"))
    return measures.provision_of(sizes, 100, 8)


def circle_marks(spark, d):
    cells = _binned(spark, d, EVENTS).groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.min("cx").alias("cx"), F.min("cy").alias("cy"))
    out = marks.circle_marks(cells.select(F.lit(1).alias("level"), F.col("cell").alias("cluster_id"), "cx", "cy", "n"))
    return out.select("cluster_id", "n", F.round("radius", 6).alias("radius"))


def heatmap_kde(spark, d):
    out = kde.heatmap(LINEITEM.pixels(spark, d, 1).select("cx", "cy"), 20.0, 30.0)
    return out.select("gx", "gy", F.round("density", 6).alias("density"))


def heatmap_raw(spark, d):
    return LINEITEM.pixels(spark, d, 1).groupBy(F.floor(F.col("cx") / 20).alias("gx"), F.floor(F.col("cy") / 20).alias("gy")).agg(F.count(F.lit(1)).alias("n"))


def _rounded_density(spark, d):
    return kde.heatmap(EVENTS.pixels(spark, d, 1).select("cx", "cy"), 25.0, 60.0).withColumn("density", F.round("density", 6))


def contour_bands(spark, d):
    rows = _rounded_density(spark, d)
    top = rows.agg(F.max("density").alias("top"))
    return rows.crossJoin(F.broadcast(top)).groupBy(F.least(F.floor(F.col("density") / F.col("top") * 5), F.lit(4)).alias("band")).agg(F.count(F.lit(1)).alias("cells"))


def contour_cells(spark, d):
    return kde.cell_cases(_rounded_density(spark, d), 5.0).where("case not in (0, 15)").select("gx", "gy", F.col("case").alias("kind"))


def contour_segments(spark, d):
    """The line pieces of two thresholds, with their ends."""
    out = kde.contours(_rounded_density(spark, d), [2.0, 5.0], 25.0)
    return out.select("threshold", *(F.round(c, 4).alias(c) for c in ("x0", "y0", "x1", "y1")))


def radar_axes(spark, d):
    """Means of eight coordinates for each label, scaled to the unit interval."""
    value = lambda k: F.element_at("embedding", k).cast("double")
    rows = table(spark, d, "embeddings").groupBy("label").agg(*(f(value(k)).alias(f"e{k}_{n}") for k in range(3, 11) for f, n in ((F.count, "cnt"), (F.sum, "sum"))))
    out = marks.radar_marks(rows, [(f"e{k}", "avg", (-0.5, 0.5)) for k in range(3, 11)])
    return out.select("label", F.posexplode("axes").alias("axis", "v")).select("label", "axis", F.round("v", 5).alias("v"))


def pie_slices(spark, d):
    rows = _binned(spark, d, PIE, "dayofweek(CAST(l_shipdate AS TIMESTAMP)) - 1 AS weekday", width=500.0)
    state = rows.groupBy(F.col("cell").alias("cluster_id"), F.col("weekday").cast("string").alias("weekday")).agg(F.count(F.lit(1)).alias("n"))
    out = marks.pie_marks(state, "weekday", domain=[str(k) for k in range(7)])
    return out.select("cluster_id", "weekday", *(F.round(c, 6).alias(c) for c in ("share", "angle0", "angle1")))


def text_marks(spark, d):
    docs = table(spark, d, "documents")
    state = docs.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.min_by("doc_id", F.struct((-F.col("n_chars")).alias("w"), "doc_id")).alias("cluster_id"))
    return marks.text_marks(state.select("cluster_id", "n"), docs.withColumnRenamed("doc_id", "obj_id"), "text")


def find_object_level(spark, d):
    return marks.find_object(_single(spark, d, CUSTOMER).marks(), 64)


def xy_correlation(spark, d):
    return EVENTS.pixels(spark, d, 1).agg(F.round(F.corr("x", "y"), 6).alias("corr"), F.round(F.corr("cx", "z"), 6).alias("corr_z"))


def binned_aggregate(spark, d):
    out = baselines.binned_aggregate(ORDERS.pixels(spark, d, 2), 100.0, 100.0)
    return out.select("bx", "by", "n", F.round("mx", 4).alias("mx"), F.round("my", 4).alias("my"))


def sampled_points(spark, d):
    return _sampled(spark, d, ORDERS).groupBy("level").agg(F.count(F.lit(1)).alias("n"))


def jittered_points(spark, d):
    out = baselines.jitter(SUPPLIER.pixels(spark, d, 1).select("obj_id", "cx", "cy"), 5.0)
    return out.select("obj_id", F.round("cx", 6).alias("cx"), F.round("cy", 6).alias("cy"))


def cell_topk(spark, d):
    return baselines.cell_topk(EVENTS.pixels(spark, d, 1), 100.0, 100.0, 3).select("obj_id", "place")


def tile_pyramid(spark, d):
    return baselines.tile_pyramid(EVENTS.pixels(spark, d, 6), 6, 500.0)


def opacity_marks(spark, d):
    cells = heatmap_raw(spark, d)
    most = F.max("n").over(W.partitionBy(F.lit(0)))  # one row for each cell of a fixed grid
    return cells.select("gx", "gy", F.round(marks.opacity(F.col("n"), most), 6).alias("opacity"))


def mark_bbox(spark, d):
    from ..functions.geometry import mark_box

    box = mark_box(F.col("cx"), F.col("cy"), 100.0, 50.0)
    return SUPPLIER.pixels(spark, d, 1).select("obj_id", box.alias("b")).select("obj_id", *(F.round(f"b.{c}", 6).alias(c) for c in ("x0", "y0", "x1", "y1")))


def _laid_out(spark, d, fixture):
    return L.layout_distributed(fixture.objects(spark, d), fixture.plan(mem_cap=2000))


def layout_overlap(spark, d):
    layout = _laid_out(spark, d, ORDERS)
    return measures.overlap_violations(layout.marks(), *layout.plan.box, layout.plan.theta)


def layout_viewport_density(spark, d):
    return measures.viewport_density(_laid_out(spark, d, SUPPLIER).marks(), 1000.0, 1000.0)


def layout_zoom_consistency(spark, d):
    layout = _laid_out(spark, d, ORDERS)
    return measures.zoom_violations(layout.visible(), layout.plan.levels)


def layout_fullness(spark, d):
    layout = _laid_out(spark, d, ORDERS)
    return measures.fullness(layout.marks(), layout.plan)


def layout_importance(spark, d):
    layout = _laid_out(spark, d, ORDERS)
    return measures.importance_by_level(layout.visible(), layout.objects)


def layout_variation(spark, d):
    """Mean distance of objects from the mark that stands for them, on every level."""
    layout = _laid_out(spark, d, ORDERS)
    return reduce(lambda a, b: a.unionByName(b), (measures.within_cluster_variation(layout, level) for level in range(1, layout.plan.levels + 1)))


def layout_object_level(spark, d):
    return marks.find_object(_laid_out(spark, d, ORDERS).marks(), 64)


QUERIES = {
    f.__name__: f
    for f in (
        agg_measures, agg_by_dimension, hover_topk, hover_bbox, hover_details, hull_area_cells, hull_area_udaf, hull_corners, agg_derived_var, rep_by_struct, overlap_violations, overlap_of_sample, viewport_density,
        zoom_consistency, fullness, importance_by_level, within_cluster_variation, mass_conservation, p95_nearest_rank, provisioning, circle_marks, heatmap_kde, heatmap_raw,
        contour_bands, contour_cells, contour_segments, radar_axes, pie_slices, text_marks, find_object_level, xy_correlation, binned_aggregate, sampled_points, jittered_points,
        cell_topk, tile_pyramid, opacity_marks, mark_bbox, layout_overlap, layout_viewport_density, layout_zoom_consistency, layout_fullness, layout_importance, layout_variation,
        layout_object_level,
    )
}

_E = _binned_sql(EVENTS)
_RANKED = f"SELECT cell, obj_id, row_number() OVER (PARTITION BY cell ORDER BY z DESC, obj_id) AS place FROM {_E}"
_HULL = _binned_sql(CUSTOMER, width=500.0)
#: Corners: no line through the point and another has points on both sides strictly, and it isn't between two others.
_CORNERS = f"""p AS (SELECT DISTINCT cell, cx AS x, cy AS y FROM {_HULL}),
  edge AS (SELECT a.cell, a.x AS ax, a.y AS ay, b.x AS qx, b.y AS qy FROM p a JOIN p b ON a.cell = b.cell AND (a.x <> b.x OR a.y <> b.y)
    WHERE NOT EXISTS (SELECT 1 FROM p c WHERE c.cell = a.cell AND (
      (b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) < -1e-7
      OR (abs((b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x)) <= 1e-7 AND ((c.x - a.x) * (b.x - a.x) + (c.y - a.y) * (b.y - a.y) < 0
          OR (c.x - b.x) * (a.x - b.x) + (c.y - b.y) * (a.y - b.y) < 0)))))"""
_KDE = "WITH p AS (SELECT cx, cy FROM {p}), s AS (SELECT floor(cx / {c}) + i AS gx, floor(cy / {c}) + j AS gy, cx, cy FROM p, range(-{r}, {r} + 1) AS a(i), range(-{r}, {r} + 1) AS b(j)), k AS (SELECT gx, gy, (((gx + 0.5) * {c} - cx) ** 2 + ((gy + 0.5) * {c} - cy) ** 2) / {b2} AS q FROM s), g AS (SELECT CAST(gx AS BIGINT) AS gx, CAST(gy AS BIGINT) AS gy, round(sum((1 - q) * (1 - q)), 6) AS density FROM k WHERE q < 1 GROUP BY gx, gy) "
_DENSITY = _KDE.format(p=EVENTS.pixels_sql(1), c=25.0, r=3, b2=3600.0)
_CASES = ", e AS (SELECT gx - i AS gx, gy - j AS gy, i + 2 * j AS c, density FROM g, range(0, 2) AS a(i), range(0, 2) AS b(j)), f AS (SELECT gx, gy, " + ", ".join(f"coalesce(max(density) FILTER (c = {k}), 0) AS {n}" for k, n in enumerate(("ll", "lr", "ul", "ur"))) + " FROM e GROUP BY gx, gy)"
_KIND = "(CASE WHEN ll >= {t} THEN 1 ELSE 0 END + CASE WHEN lr >= {t} THEN 2 ELSE 0 END + CASE WHEN ur >= {t} THEN 4 ELSE 0 END + CASE WHEN ul >= {t} THEN 8 ELSE 0 END)"
_SAMPLE = _sampled_sql(ORDERS)


def _single_sql(fixture):
    """Marks of the one-task layout: level, cluster_id, z, cx, cy."""
    return (
        f"(SELECT e.level, e.child AS cluster_id, p.z, p.cx * pow(2.0, e.level - 6) AS cx, p.cy * pow(2.0, e.level - 6) AS cy "
        f"FROM ({greedy_sql(fixture, 6)}) e JOIN {fixture.pixels_sql(6)} p ON p.obj_id = e.child WHERE e.child = e.parent)"
    )


_MARKS = _single_sql(CUSTOMER)
_NEAR = "greatest(abs(a.cx - b.cx) / 100.0, abs(a.cy - b.cy) / 100.0)"
SQL = {
    "agg_measures": f"SELECT cell, count(z) AS n, round(sum(z), 4) AS total, round(avg(z), 6) AS mean, min(z) AS least, max(z) AS most, round(sum(z * z), 2) AS squares FROM {_E} GROUP BY cell",
    "agg_by_dimension": f"SELECT cell, event_type, count(*) AS n, round(sum(z), 4) AS total FROM {_binned_sql(EVENTS, 'event_type')} GROUP BY ALL",
    "hover_topk": f"SELECT cell, place, obj_id FROM ({_RANKED}) WHERE place <= 3",
    "hover_bbox": f"SELECT cell, round(min(x), 6) AS x0, round(min(y), 6) AS y0, round(max(x), 6) AS x1, round(max(y), 6) AS y1 FROM {_E} GROUP BY cell",
    "hover_details": f"SELECT cell, obj_id, user_id, event_type, value FROM ({_RANKED}) JOIN events ON obj_id = event_id WHERE place = 1",
    "hull_area_cells": f"WITH {_CORNERS} SELECT cell, round(coalesce(abs(sum(ax * qy - ay * qx)) / 2, 0), 4) AS area FROM (SELECT DISTINCT cell FROM p) LEFT JOIN edge USING (cell) GROUP BY cell",
    "hull_area_udaf": f"WITH {_CORNERS.replace(_HULL, _binned_sql(SUPPLIER, width=500.0))} SELECT cell, round(coalesce(abs(sum(ax * qy - ay * qx)) / 2, 0), 4) AS area FROM (SELECT DISTINCT cell FROM p) LEFT JOIN edge USING (cell) GROUP BY cell",
    "hull_corners": f"WITH {_CORNERS} SELECT cell, round(ax, 6) AS x, round(ay, 6) AS y FROM edge UNION SELECT cell, round(x, 6), round(y, 6) FROM p WHERE cell IN (SELECT cell FROM p GROUP BY cell HAVING count(*) < 3)",
    "agg_derived_var": f"SELECT cell, round(greatest(sum(z * z) / count(z) - avg(z) * avg(z), 0), 4) AS variance FROM {_E} GROUP BY cell",
    "rep_by_struct": f"SELECT cell, obj_id AS rep FROM ({_RANKED}) WHERE place = 1",
    "overlap_violations": f"WITH m AS (SELECT * FROM {_MARKS}), v AS (SELECT a.level, count(*) AS n FROM m a JOIN m b ON a.level = b.level AND a.cluster_id < b.cluster_id AND abs(a.cx - b.cx) < 100 AND {_NEAR} < (1 - 1e-9) GROUP BY 1) SELECT l.level, coalesce(n, 0) AS violations FROM (SELECT DISTINCT level FROM m) l LEFT JOIN v ON l.level = v.level",
    "overlap_of_sample": f"WITH m AS (SELECT * FROM {_SAMPLE}), v AS (SELECT a.level, count(*) AS n FROM m a JOIN m b ON a.level = b.level AND a.cluster_id < b.cluster_id AND abs(a.cx - b.cx) < 100 AND {_NEAR} < (1 - 1e-9) GROUP BY 1) SELECT l.level, coalesce(n, 0) AS violations FROM (SELECT DISTINCT level FROM m) l LEFT JOIN v ON l.level = v.level",
    "viewport_density": f"""WITH m AS (SELECT * FROM {_single_sql(SUPPLIER)}), w AS (SELECT DISTINCT a.level, a.cx AS x0, b.cy AS y0 FROM m a JOIN m b ON a.level = b.level AND b.cx >= a.cx AND b.cx < a.cx + 1000 AND b.cy <= a.cy AND a.cy < b.cy + 1000),
      n AS (SELECT w.level, x0, y0, count(*) AS n FROM w JOIN m ON m.level = w.level AND m.cx >= x0 AND m.cx < x0 + 1000 AND m.cy >= y0 AND m.cy < y0 + 1000 GROUP BY ALL) SELECT level, max(n) AS most FROM n GROUP BY level""",
    "zoom_consistency": f"WITH s AS (SELECT level, cluster_id FROM {_MARKS}) SELECT a.level, a.cluster_id FROM s a WHERE a.level < 6 AND NOT EXISTS (SELECT 1 FROM s b WHERE b.level = a.level + 1 AND b.cluster_id = a.cluster_id)",
    "fullness": f"""SELECT level, count(*) AS marks, CAST(pow(10 * pow(2, level - 1) + 1, 2) AS BIGINT) AS capacity, round(count(*) / pow(10 * pow(2, level - 1) + 1, 2), 9) AS share,
      round(count(DISTINCT (floor(cx / 100), floor(cy / 100))) / pow(10 * pow(2, level - 1) + 1, 2), 9) AS occupied FROM {_MARKS} GROUP BY level""",
    "importance_by_level": f"""WITH r AS (SELECT obj_id, percent_rank() OVER (ORDER BY z) AS p FROM {CUSTOMER.pixels_sql(1)})
      SELECT level, round(avg(p), 6) AS mean_rank, round(count(*) FILTER (p >= 0.9) / (SELECT count(*) FROM r WHERE p >= 0.9), 6) AS top_visible FROM {_MARKS} s JOIN r ON s.cluster_id = r.obj_id GROUP BY level""",
    "within_cluster_variation": "WITH e AS (SELECT * FROM (" + greedy_sql(CUSTOMER, 6) + ")), m6 AS (SELECT child AS o, parent AS c FROM e WHERE level = 6), "
    + ", ".join(f"m{k} AS (SELECT o, parent AS c FROM m{k + 1} JOIN e ON e.level = {k} AND e.child = m{k + 1}.c)" for k in range(5, 0, -1))
    + f", p AS (SELECT * FROM {CUSTOMER.pixels_sql(1)}) SELECT level, round(avg(sqrt((a.cx - b.cx) ** 2 + (a.cy - b.cy) ** 2) * pow(2, level - 1)), 6) AS variation FROM ("
    + " UNION ALL ".join(f"SELECT {k} AS level, o, c FROM m{k}" for k in range(1, 7))
    + ") m JOIN p a ON a.obj_id = m.o JOIN p b ON b.obj_id = m.c GROUP BY level",
    "mass_conservation": f"SELECT count(*) AS objects, round(sum(z), 3) AS total FROM {_E}",
    "p95_nearest_rank": "SELECT event_type, quantile_disc(value, 0.95) AS p95 FROM events GROUP BY 1",
    "provisioning": "SELECT l_quantity, n AS objects, CAST(ceil(n / 100) AS BIGINT) AS partitions, CAST(ceil(ceil(n / 100) / 8) AS BIGINT) AS nodes FROM (SELECT l_quantity, count(*) AS n FROM lineitem GROUP BY 1)",
    "circle_marks": f"SELECT cell AS cluster_id, n, round(25.0 * sqrt(n / max(n) OVER ()), 6) AS radius FROM (SELECT cell, count(*) AS n FROM {_E} GROUP BY cell)",
    "heatmap_kde": _KDE.format(p=LINEITEM.pixels_sql(1), c=20.0, r=2, b2=900.0) + "SELECT * FROM g",
    "heatmap_raw": f"SELECT CAST(floor(cx / 20) AS BIGINT) AS gx, CAST(floor(cy / 20) AS BIGINT) AS gy, count(*) AS n FROM {LINEITEM.pixels_sql(1)} GROUP BY ALL",
    "contour_bands": _DENSITY + "SELECT CAST(least(floor(density / (SELECT max(density) FROM g) * 5), 4) AS BIGINT) AS band, count(*) AS cells FROM g GROUP BY 1",
    "contour_cells": _DENSITY + _CASES + f" SELECT gx, gy, {_KIND.format(t=5.0)} AS kind FROM f WHERE {_KIND.format(t=5.0)} NOT IN (0, 15)",
    "contour_segments": _DENSITY + _CASES + f""", side(k, a, b) AS (VALUES {", ".join(f"({case}, {a}, {b})" for case, lines in kde.SEGMENTS.items() for a, b in lines)}),
      t(t) AS (VALUES (2.0::DOUBLE), (5.0)), kind AS (SELECT *, {_KIND.format(t="t")} AS k, (gx + 0.5) * 25.0 AS x, (gy + 0.5) * 25.0 AS y FROM f, t),
      corner AS (SELECT *, [x + (t - ll) / (lr - ll) * 25.0, x + 25.0, x + (t - ul) / (ur - ul) * 25.0, x] AS px, [y, y + (t - lr) / (ur - lr) * 25.0, y + 25.0, y + (t - ll) / (ul - ll) * 25.0] AS py FROM kind)
      SELECT t AS threshold, round(px[a + 1], 4) AS x0, round(py[a + 1], 4) AS y0, round(px[b + 1], 4) AS x1, round(py[b + 1], 4) AS y1 FROM corner JOIN side USING (k)""",
    "radar_axes": "SELECT label, axis, round(least(greatest(v + 0.5, 0), 1), 5) AS v FROM (SELECT label, i AS axis, avg(embedding[i + 3]::DOUBLE) AS v FROM embeddings, range(0, 8) AS t(i) GROUP BY ALL)",
    "pie_slices": f"""WITH s AS (SELECT cell, CAST(dayofweek(l_shipdate) AS VARCHAR) AS weekday, count(*) AS n FROM {_binned_sql(PIE, 'l_shipdate', width=500.0)} GROUP BY ALL),
      w AS (SELECT *, n / sum(n) OVER (PARTITION BY cell) AS share, sum(n) OVER (PARTITION BY cell ORDER BY weekday) / sum(n) OVER (PARTITION BY cell) AS e FROM s)
      SELECT cell AS cluster_id, weekday, round(share, 6) AS share, round((e - share) * 2 * pi(), 6) AS angle0, round(e * 2 * pi(), 6) AS angle1 FROM w""",
    "text_marks": "SELECT cluster_id, n, text FROM (SELECT arg_min(doc_id, (-n_chars, doc_id)) AS cluster_id, count(*) AS n FROM documents GROUP BY lang) JOIN documents ON doc_id = cluster_id",
    "find_object_level": f"SELECT CAST(64 AS INTEGER) AS obj_id, min(level) AS level FROM {_MARKS} WHERE cluster_id = 64",
    "xy_correlation": f"SELECT round(corr(x, y), 6) AS corr, round(corr(cx, z), 6) AS corr_z FROM {EVENTS.pixels_sql(1)}",
    "binned_aggregate": f"SELECT CAST(floor(cx / 100) AS BIGINT) AS bx, CAST(floor(cy / 100) AS BIGINT) AS by, count(*) AS n, round(avg(cx), 4) AS mx, round(avg(cy), 4) AS my FROM {ORDERS.pixels_sql(2)} GROUP BY ALL",
    "sampled_points": f"SELECT level, count(*) AS n FROM {_SAMPLE} GROUP BY level",
    "jittered_points": f"SELECT obj_id, round(cx + ((obj_id * 7919 % 1009) / 1008.0 - 0.5) * 2 * 5.0, 6) AS cx, round(cy + ((obj_id * 104729 % 1009) / 1008.0 - 0.5) * 2 * 5.0, 6) AS cy FROM {SUPPLIER.pixels_sql(1)}",
    "cell_topk": f"SELECT obj_id, place FROM (SELECT obj_id, row_number() OVER (PARTITION BY floor(cx / 100), floor(cy / 100) ORDER BY z DESC, obj_id) AS place FROM {EVENTS.pixels_sql(1)}) WHERE place <= 3",
    "tile_pyramid": f"SELECT l.level, CAST(floor(cx / 500 / pow(2, 6 - l.level)) AS BIGINT) AS tx, CAST(floor(cy / 500 / pow(2, 6 - l.level)) AS BIGINT) AS ty, count(*) AS n FROM {EVENTS.pixels_sql(6)}, range(1, 7) AS l(level) GROUP BY ALL",
    "opacity_marks": f"SELECT gx, gy, round(least(1.0, 0.2 + 0.8 * n / max(n) OVER ()), 6) AS opacity FROM (SELECT CAST(floor(cx / 20) AS BIGINT) AS gx, CAST(floor(cy / 20) AS BIGINT) AS gy, count(*) AS n FROM {LINEITEM.pixels_sql(1)} GROUP BY ALL)",
    "mark_bbox": f"SELECT obj_id, round(cx - 50, 6) AS x0, round(cy - 25, 6) AS y0, round(cx + 50, 6) AS x1, round(cy + 25, 6) AS y1 FROM {SUPPLIER.pixels_sql(1)}",
}
