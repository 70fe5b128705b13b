"""The experiment workloads, re-expressed on the given tables, each as a document."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import kde, marks
from ..operators import layout as L
from ..operators.rollup import all_levels, value_of
from .materialize import materialize
from ..sources.fixtures import LINE_ID, register, skewed
from .spec import (
    AggFn, Aggregate, Axis, Boundary, ClusterMark, Compiled, Config, CustomRef, Dimension, HoverMark, Importance, LayoutSpec, Marks, Measure, Mode, Ranklist, ScatterSpec, compile_spec,
)

_COUNT = Measure("*", AggFn.COUNT)


def _spec(mode: Mode, data: str, x: Axis, y: Axis, z: str, config: Config, measures=(_COUNT,), dimensions=(), hover=None, theta=None, custom=None) -> ScatterSpec:
    return ScatterSpec(Marks(ClusterMark(mode, Aggregate(tuple(measures), tuple(dimensions)), custom), hover), LayoutSpec(x, y, Importance(z), theta), data, config)


_LINES = f"SELECT {LINE_ID} AS id, l_quantity, l_extendedprice, l_shipdate FROM lineitem"
HEATMAP = _spec(Mode.HEATMAP, _LINES, Axis("l_quantity", (0.0, 51.0)), Axis("l_extendedprice", (0.0, 105000.0)), "l_shipdate", Config(id="id", num_levels=10, mem_cap=6700, density_cap=10_000))
CONTOUR = HEATMAP.with_mode(Mode.CONTOUR)
EVENT_CONTOUR = _spec(Mode.CONTOUR, "SELECT event_id, ts, value FROM events", Axis("ts"), Axis("value"), "value", Config(id="event_id", num_levels=10, mem_cap=2000, density_cap=10_000))
PROFILE = _spec(
    Mode.CUSTOM,
    "SELECT c_custkey, c_name, n_name, c_acctbal, coalesce(total, 0.0D) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey LEFT JOIN (SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey) ON c_custkey = o_custkey",
    Axis("c_acctbal"), Axis("total"), "total", Config(id="c_custkey", box_width=160.0, box_height=130.0), theta=0.5, custom=CustomRef("profile"),
)
PIES = _spec(
    Mode.PIE, f"SELECT {LINE_ID} AS id, log10(l_extendedprice / l_quantity) AS unit_price, l_quantity, l_shipdate, dayofweek(CAST(l_shipdate AS TIMESTAMP)) - 1 AS weekday FROM lineitem",
    Axis("unit_price", (0.0, 5.5)), Axis("l_quantity", (0.0, 51.0)), "l_shipdate", Config(id="id", num_levels=8, mem_cap=67_000),
    measures=(_COUNT, Measure("l_quantity", AggFn.SUM)), dimensions=(Dimension("weekday", tuple(map(str, range(7)))),), hover=HoverMark(Ranklist(3), Boundary.HULL),
)
TEXT = _spec(
    Mode.CUSTOM,
    "SELECT doc_id, substring(text, 1, 200) AS text, ln(greatest(n_chars, 1)) AS size, CAST(size(array_distinct(split(text, ' '))) AS DOUBLE) AS words, coalesce(quality, 0) * 1.0E7D + n_chars AS importance FROM documents LEFT JOIN labels USING (doc_id)",
    Axis("size"), Axis("words"), "importance", Config(id="doc_id", num_levels=20, mem_cap=1250, box_width=200.0, box_height=60.0), theta=1.0, custom=CustomRef("text"),
)
CIRCLE = _spec(
    Mode.CIRCLE, "SELECT event_id, ts, value, event_type FROM events", Axis("ts"), Axis("value"), "value", Config(id="event_id", num_levels=15, mem_cap=2000),
    hover=HoverMark(Ranklist(3), Boundary.BBOX),
)
RADAR = _spec(
    Mode.RADAR, "SELECT vec_id, label, " + ", ".join(f"CAST(element_at(embedding, {k}) AS DOUBLE) AS e{k}" for k in range(1, 12)) + " FROM embeddings",
    Axis("e1", (-0.5, 0.5)), Axis("e2", (-0.5, 0.5)), "e11", Config(id="vec_id"), measures=tuple(Measure(f"e{k}", AggFn.AVG, (-0.5, 0.5)) for k in range(3, 11)), hover=HoverMark(Ranklist(3)),
)
SPECS: dict[str, ScatterSpec] = {
    "heatmap_lineitem": HEATMAP, "contour_lineitem": CONTOUR, "contour_events": EVENT_CONTOUR, "profile_customer": PROFILE, "pie_lineitem": PIES, "text_documents": TEXT, "circle_events": CIRCLE, "radar_embeddings": RADAR,
}


def compiled(spark: SparkSession, sf_dir: str, spec: ScatterSpec) -> Compiled:
    register(spark, sf_dir)
    return compile_spec(spark, spec)


def lay_out(spark: SparkSession, sf_dir: str, spec: ScatterSpec, **options) -> L.Layout:
    c = compiled(spark, sf_dir, spec)
    return L.layout_distributed(c.objects, c.plan, **options)


def statistics(layout: L.Layout, spec: ScatterSpec) -> DataFrame:
    """States of all levels, as the document's aggregate and hover ask for."""
    agg, hover = spec.marks.cluster.aggregate, spec.marks.hover
    sources = {f"m{k}": m.field for k, m in enumerate(agg.measures) if m.field != "*"}
    ranks = hover.ranklist.k if hover and hover.ranklist else 0
    hull = bool(hover and hover.boundary is Boundary.HULL)
    return all_levels(layout, measures=sources, dimensions=[d.field for d in agg.dimensions], k=ranks, hull=hull)


def payload(layout: L.Layout, spec: ScatterSpec) -> DataFrame:
    """What a client draws of each mark: level, cluster_id, n; a column for each measure; slices (value of the
    dimension to count); top (ids of the most important objects); box or hull of the members."""
    agg, hover = spec.marks.cluster.aggregate, spec.marks.hover
    measures = {f"m{k}": m for k, m in enumerate(agg.measures) if m.field != "*"}
    ranks = hover.ranklist.k if hover and hover.ranklist else 0
    hull = bool(hover and hover.boundary is Boundary.HULL)
    state = all_levels(layout, measures={n: m.field for n, m in measures.items()}, k=ranks, hull=hull)
    cols = ["level", "cluster_id", "n", *(value_of(n, m.function.value).alias(f"{m.function.value}_{m.field}") for n, m in measures.items())]
    cols += [F.col("topk.obj_id").alias("top")] if ranks else []
    if hover and hover.boundary is not None:
        cols.append(F.col("hull") if hull else F.struct("x0", "y0", "x1", "y1").alias("members_box"))
    out = state.select(*cols)
    if agg.dimensions:
        names = [d.field for d in agg.dimensions]
        parts = all_levels(layout, dimensions=names)
        key = F.concat_ws("|", *names)  # as many as the domains have, whatever the cluster's size
        slices = parts.groupBy("level", "cluster_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct(key.alias("key"), F.col("n").alias("value"))))).alias("slices"))
        out = out.join(slices, ["level", "cluster_id"])
    return out


def marks_with_payload(layout: L.Layout, spec: ScatterSpec) -> DataFrame:
    """Marks of all levels with their places, payload, and what the document's mode draws of them."""
    rows = layout.marks().join(payload(layout, spec), ["level", "cluster_id"])
    mode, custom = spec.marks.cluster.mode, spec.marks.cluster.custom
    if mode is Mode.CIRCLE:
        size = marks.circle_marks(rows, spec.config.max_radius).select("level", "cluster_id", "radius")
        rows = rows.join(size, ["level", "cluster_id"])
    elif mode is Mode.RADAR:
        axes = [(f"{m.function.value}_{m.field}", m.extent) for m in spec.marks.cluster.aggregate.measures]
        rows = rows.withColumn("axes", marks.radar_axes(axes))
    elif mode is Mode.CUSTOM and custom is not None:
        rows = marks.custom_payload(rows, layout.objects, custom.name)
    return rows


def synthetic(spark: SparkSession, sf_dir: str, parts: int = 1, leaves: int = 500) -> L.Layout:
    """The skewed synthetic circles, one of `parts` of the objects, as many leaves as asked for."""
    objects = skewed(spark, sf_dir, parts)
    total = objects.count()
    return L.layout_distributed(objects, L.LayoutPlan((0.0, 1.0), (0.0, 1.0), levels=8, mem_cap=max(1, total // leaves)))


def _per_level(layout: L.Layout) -> DataFrame:
    return layout.visible().groupBy("level").count().withColumnRenamed("count", "marks")


def density_of_level(layout: L.Layout, spec: ScatterSpec, level: int, cell: float = 10.0) -> DataFrame:
    """(gx, gy, density): the density grid of a level, from its marks weighted by the objects they stand for."""
    rows = layout.marks(level).join(payload(layout, spec).where(F.col("level") == level).select("cluster_id", "n"), "cluster_id")
    return kde.heatmap(rows, cell, spec.config.bandwidth, F.col("n"))


def contour_lines(layout: L.Layout, spec: ScatterSpec, level: int, bands: int = 5, cell: float = 10.0) -> DataFrame:
    """(threshold, x0, y0, x1, y1): the contour lines of a level."""
    density = materialize(density_of_level(layout, spec, level, cell), "density")
    return kde.contours(density, kde.thresholds(density, bands), cell)


def smaller(spec: ScatterSpec, levels: int) -> ScatterSpec:
    return replace(spec, config=replace(spec.config, num_levels=levels))
