"""Cluster statistics that merge as clusters merge: counts, sums, extremes, top lists, boundaries.

The state of a level is the state of the level below, joined with that level's edges and combined per
parent.  All merges are algebraic, so Spark combines them before the shuffle, and every level is smaller
than the one below.  Lists hold ids and places only; other columns come by a late join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from ..plans.materialize import materialize
from .kernels import convex_hull, polygon_area
from .layout import Layout

_POINTS = T.ArrayType(T.StructType([T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())]))


@F.pandas_udf(_POINTS)
def hull_of(points: pd.Series) -> pd.Series:
    """Corners of the convex hull of an array of points."""

    def one(ps) -> list[dict]:
        if ps is None:
            return []
        return [{"x": float(a), "y": float(b)} for a, b in convex_hull(np.array([(p["x"], p["y"]) for p in ps], float))]

    return points.map(one)


@F.pandas_udf(T.DoubleType())
def hull_area_of(x: pd.Series, y: pd.Series) -> float:
    """Aggregate: area of the convex hull of a group's points; for groups of a bounded size."""
    return float(polygon_area(convex_hull(np.stack([x.to_numpy(float), y.to_numpy(float)], axis=1))))


@F.pandas_udf(T.DoubleType())
def hull_area(points: pd.Series) -> pd.Series:
    return points.map(lambda ps: polygon_area(convex_hull(np.array([(p["x"], p["y"]) for p in ps], float))) if ps is not None and len(ps) else 0.0)


def single_state(layout: Layout, measures: dict[str, str], dimensions: list[str], k: int, hull: bool) -> DataFrame:
    """State of the objects, each a cluster of its own.  measures: name to column."""
    cols: list[Column] = [F.col("obj_id").alias("cluster_id"), F.lit(1).cast("long").alias("n")]
    for name, source in measures.items():
        v = F.col(source).cast("double")
        cols += [v.isNotNull().cast("long").alias(f"{name}_cnt"), v.alias(f"{name}_sum"), (v * v).alias(f"{name}_sumsq"), v.alias(f"{name}_min"), v.alias(f"{name}_max")]
    cols += [F.col("x").alias("x0"), F.col("y").alias("y0"), F.col("x").alias("x1"), F.col("y").alias("y1")]
    cols += [F.col(d).cast("string").alias(d) for d in dimensions]
    if k:
        w = -F.col("z") if layout.plan.descending else F.col("z")
        cols.append(F.array(F.struct(F.coalesce(w, F.lit(float("inf"))).alias("w"), F.col("obj_id").alias("obj_id"))).alias("topk"))
    if hull:
        cols.append(F.array(F.struct("x", "y")).alias("hull"))
    return layout.objects.select(*cols)


#: Children whose top lists or boundaries one row gathers.
GATHERED = 1024


def _top_lists(state: DataFrame, keys: list[str], k: int) -> DataFrame:
    """(keys, topk): of all lists under a key the first k entries; ranks prune to k a task before the shuffle."""
    first = W.partitionBy(*keys).orderBy("t.w", "t.obj_id")
    rows = state.select(*keys, F.explode("topk").alias("t")).withColumn("place", F.row_number().over(first)).where(F.col("place") <= k)
    return rows.groupBy(*keys).agg(F.array_sort(F.collect_list("t")).alias("topk"))


def _hulls(state: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, hull): boundaries of at most GATHERED children are merged at once, then those of the merged."""
    number = F.row_number().over(W.partitionBy(*keys).orderBy(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1")))
    dealt = state.select(*keys, "hull", F.floor((number - 1) / GATHERED).alias("part"))
    once = dealt.groupBy(*keys, "part").agg(F.flatten(F.collect_list("hull")).alias("hull")).withColumn("hull", hull_of("hull"))
    return once.groupBy(*keys).agg(F.flatten(F.collect_list("hull")).alias("hull")).withColumn("hull", hull_of("hull"))


def _merged(state: DataFrame, keys: list[str], measures: dict[str, str], k: int, hull: bool) -> DataFrame:
    aggs = [F.sum("n").alias("n")]
    for name in measures:
        aggs += [F.sum(f"{name}_{s}").alias(f"{name}_{s}") for s in ("cnt", "sum", "sumsq")]
        aggs += [F.min(f"{name}_min").alias(f"{name}_min"), F.max(f"{name}_max").alias(f"{name}_max")]
    aggs += [F.min("x0").alias("x0"), F.min("y0").alias("y0"), F.max("x1").alias("x1"), F.max("y1").alias("y1")]
    out = state.groupBy(*keys).agg(*aggs)
    for wanted, part in ((k, lambda: _top_lists(state, keys, k)), (hull, lambda: _hulls(state, keys))):
        if wanted:
            more = part()
            same = [out[c].eqNullSafe(more[c]) for c in keys]
            both = same[0]
            for c in same[1:]:
                both = both & c
            out = out.join(more, both).select(*(out[c] for c in out.columns), more[more.columns[-1]])
    return out


def roll_up(layout: Layout, measures: dict[str, str] | None = None, dimensions: list[str] | None = None, k: int = 0, hull: bool = False) -> Iterator[tuple[int, DataFrame]]:
    """(level, state) from the bottom to the top; one row for each cluster, and value of the dimensions if there are."""
    measures, dimensions = measures or {}, dimensions or []
    state = single_state(layout, measures, dimensions, k, hull)
    for level in range(layout.plan.levels, 0, -1):
        edges = layout.edges.where(F.col("level") == level).select(F.col("child").alias("cluster_id"), "parent")
        joined = state.join(edges, "cluster_id").drop("cluster_id").withColumnRenamed("parent", "cluster_id")
        state = materialize(_merged(joined, ["cluster_id", *dimensions], measures, k, hull), f"state-{level}")
        yield level, state


def all_levels(layout: Layout, **options) -> DataFrame:
    """The states of all levels, with the column level."""
    out = None
    for level, state in roll_up(layout, **options):
        part = state.withColumn("level", F.lit(level).cast("int"))
        out = part if out is None else out.unionByName(part)
    return out


def value_of(name: str, function: str) -> Column:
    """A measure's value from its state."""
    if function == "count":
        return F.col(f"{name}_cnt").cast("double")
    if function == "avg":
        return F.try_divide(F.col(f"{name}_sum"), F.col(f"{name}_cnt").cast("double"))
    column = {"sum": "sum", "sqrsum": "sumsq", "min": "min", "max": "max"}[function]
    return F.col(f"{name}_{column}")


def variance_of(name: str) -> Column:
    mean = F.try_divide(F.col(f"{name}_sum"), F.col(f"{name}_cnt").cast("double"))
    return F.greatest(F.try_divide(F.col(f"{name}_sumsq"), F.col(f"{name}_cnt").cast("double")) - mean * mean, F.lit(0.0))


def zero_filled(state: DataFrame, dimension: str, domain: list[str]) -> DataFrame:
    """A row for each cluster and value of the domain; n is 0 where a cluster has none."""
    wanted = state.select("cluster_id").distinct().withColumn(dimension, F.explode(F.array(*(F.lit(d) for d in domain))))
    return wanted.join(state, ["cluster_id", dimension], "left").withColumn("n", F.coalesce("n", F.lit(0)))


def hover_details(layout: Layout, state: DataFrame) -> DataFrame:
    """(cluster_id, place, and all columns of the object) for the top lists of a state."""
    ranks = state.select("cluster_id", F.posexplode("topk").alias("place", "t")).select("cluster_id", (F.col("place") + 1).alias("place"), F.col("t.obj_id").alias("obj_id"))
    return ranks.join(layout.objects, "obj_id")
