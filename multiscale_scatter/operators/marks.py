"""Payloads of the mark families: what a client needs to draw them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from ..functions import geometry as G
from .layout import LayoutPlan
from .rollup import value_of


def circle_marks(marks: DataFrame, max_radius: float = 25.0) -> DataFrame:
    """marks(level, cluster_id, cx, cy, n) with radius: areas in proportion to the counts of a level."""
    most = F.max("n").over(W.partitionBy("level"))
    return marks.select("level", "cluster_id", "cx", "cy", "n", (F.lit(float(max_radius)) * F.sqrt(F.col("n") / most)).alias("radius"))


def radar_axes(axes: list[tuple[str, tuple[float, float]]]) -> Column:
    """Each value column (name, extent) scaled to 0..1, as an array in their order."""
    scaled = lambda name, extent: F.least(F.greatest((F.col(name) - extent[0]) / (extent[1] - extent[0]), F.lit(0.0)), F.lit(1.0))
    return F.array(*(scaled(*a) for a in axes))


def radar_marks(state: DataFrame, axes: list[tuple[str, str, tuple[float, float]]]) -> DataFrame:
    """state with axes(array): each measure (name, function, extent) scaled to 0..1."""
    named = state.withColumns({f"__{k}": value_of(name, function) for k, (name, function, _) in enumerate(axes)})
    return named.withColumn("axes", radar_axes([(f"__{k}", extent) for k, (_, _, extent) in enumerate(axes)])).drop(*(f"__{k}" for k in range(len(axes))))


def pie_marks(state: DataFrame, dimension: str, value: str = "n", domain: list[str] | None = None) -> DataFrame:
    """(cluster_id, dimension, share, angle0, angle1) in the order of the domain; values it lacks are left out."""
    place = F.array_position(F.array(*(F.lit(d) for d in domain)), F.col(dimension)) if domain else F.col(dimension)
    rows = state.where(place > 0) if domain else state
    whole = W.partitionBy("cluster_id")
    running = whole.orderBy(place).rowsBetween(W.unboundedPreceding, 0)
    share = F.col(value) / F.sum(value).over(whole)
    end = F.sum(value).over(running) / F.sum(value).over(whole)
    turn = 2 * 3.141592653589793
    return rows.select("cluster_id", dimension, share.alias("share"), ((end - share) * turn).alias("angle0"), (end * turn).alias("angle1"))


def text_marks(state: DataFrame, objects: DataFrame, text: str) -> DataFrame:
    """state(cluster_id, n, ...) with text, the representative's; how much of it is shown is the client's matter."""
    return state.join(objects.select(F.col("obj_id").alias("cluster_id"), F.col(text).alias("text")), "cluster_id")


def custom_marks(payload: DataFrame, fn: Callable[[dict], dict], schema: str | T.StructType) -> DataFrame:
    """Any function of a cluster's full payload."""
    names = [f.name for f in (T._parse_datatype_string(schema) if isinstance(schema, str) else schema).fields]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield pd.DataFrame([fn(r) for r in pdf.to_dict("records")], columns=names)

    return payload.mapInPandas(run, schema)


def custom_payload(marks: DataFrame, objects: DataFrame, name: str) -> DataFrame:
    """marks with the payload of a named renderer: "text" has the representative's text and how many it stands for,
    "profile" a card of all its columns."""
    own = objects.withColumnRenamed("obj_id", "cluster_id").drop("x", "y", "z")
    if name == "text":
        return marks.join(text_marks(marks.select("level", "cluster_id", "n"), objects, "text").drop("n"), ["level", "cluster_id"])
    card = own.select("cluster_id", F.to_json(F.struct(*(c for c in own.columns if c != "cluster_id"))).alias("card"))
    return marks.join(card, "cluster_id")


def axis_ticks(plan: LayoutPlan, level: int, count: int = 10) -> list[tuple[str, float, float]]:
    """(axis, raw value, pixel) of evenly spaced ticks."""
    out = []
    for name, (lo, hi), size in (("x", plan.x_extent, plan.top[0]), ("y", plan.y_extent, plan.top[1])):
        full = G.level_size(size, plan.zoom, level)
        out += [(name, lo + (hi - lo) * k / count, full * k / count) for k in range(count + 1)]
    return out


def legend(counts: list[int], max_radius: float = 25.0) -> list[tuple[int, float]]:
    """(count, radius) samples for circles."""
    most = max(counts, default=1)
    return [(c, max_radius * (c / most) ** 0.5) for c in sorted(set(counts))]


def find_object(visible: DataFrame, obj_id: int) -> DataFrame:
    """(obj_id, level) on which an object is first visible."""
    return visible.where(F.col("cluster_id") == obj_id).agg(F.min("level").alias("level")).select(F.lit(obj_id).alias("obj_id"), "level")


def compare(objects: DataFrame, ids: list[int]) -> DataFrame:
    return objects.where(F.col("obj_id").isin(ids))


def opacity(n: Column, most: Column) -> Column:
    """Appearance instead of layout: denser marks more opaque."""
    return F.least(F.lit(1.0), 0.2 + 0.8 * n / most)
