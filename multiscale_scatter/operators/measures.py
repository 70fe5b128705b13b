"""Cost and accuracy measures of layouts, as DataFrame operations over marks(level, cluster_id, cx, cy, ...)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions import geometry as G
from ..plans.materialize import materialize
from .layout import Layout, LayoutPlan


def close_pairs(marks: DataFrame, wb: float, hb: float, theta: float) -> DataFrame:
    """(level, id1, id2, d): marks of a level closer than theta, each pair once.

    Found through cells of side theta: a mark meets its own cell and the eight around it.
    """
    w, h = wb * theta, hb * theta
    steps = F.array(*(F.lit(k) for k in (-1, 0, 1)))
    left = marks.select("level", F.col("cluster_id").alias("id1"), F.col("cx").alias("x1"), F.col("cy").alias("y1"))
    left = left.withColumn("dx", F.explode(steps)).withColumn("dy", F.explode(steps))
    left = left.select("level", "id1", "x1", "y1", (F.floor(F.col("x1") / w) + F.col("dx")).alias("a"), (F.floor(F.col("y1") / h) + F.col("dy")).alias("b"))
    right = marks.select("level", F.col("cluster_id").alias("id2"), F.col("cx").alias("x2"), F.col("cy").alias("y2"), F.floor(F.col("cx") / w).alias("a"), F.floor(F.col("cy") / h).alias("b"))
    d = G.ncd(F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"), wb, hb)
    # sizes of files say little of the rows in them, so neither side may be broadcast
    return left.join(right.hint("merge"), ["level", "a", "b"]).where((F.col("id1") < F.col("id2")) & (d < theta)).select("level", "id1", "id2", d.alias("d"))


def overlap_violations(marks: DataFrame, wb: float, hb: float, theta: float) -> DataFrame:
    """(level, violations), levels without any too; what is closer by rounding alone is none.

    Marks of one place are counted, not paired: k of them have k (k - 1) / 2 pairs, and those of two places
    that are too close the product of their numbers.  Ids are unique on a level.
    """
    near = theta * (1 - 1e-9)
    w, h = wb * near, hb * near
    places = marks.groupBy("level", "cx", "cy").agg(F.count(F.lit(1)).alias("n"))
    inside = places.where(G.ncd(F.col("cx"), F.col("cy"), F.col("cx"), F.col("cy"), wb, hb) < near).select("level", (F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("pairs"))
    if near > 0:
        cell = lambda c, s: F.floor(F.col(c) / s)
        # a place meets its own cell and half of those around it, so each pair of places once
        steps = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in ((0, 0), (0, 1), (1, -1), (1, 0), (1, 1))))
        left = places.select("level", F.col("cx").alias("x1"), F.col("cy").alias("y1"), F.col("n").alias("n1"), cell("cx", w).alias("a1"), cell("cy", h).alias("b1"), F.explode(steps).alias("s"))
        left = left.select("level", "x1", "y1", "n1", (F.col("a1") + F.col("s.i")).alias("a"), (F.col("b1") + F.col("s.j")).alias("b"), ((F.col("s.i") == 0) & (F.col("s.j") == 0)).alias("own"))
        right = places.select("level", F.col("cx").alias("x2"), F.col("cy").alias("y2"), F.col("n").alias("n2"), cell("cx", w).alias("a"), cell("cy", h).alias("b"))
        later = ~F.col("own") | (F.col("x1") < F.col("x2")) | ((F.col("x1") == F.col("x2")) & (F.col("y1") < F.col("y2")))
        met = left.join(right.hint("merge"), ["level", "a", "b"]).where(later & (G.ncd(F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"), wb, hb) < near))
        inside = inside.unionByName(met.select("level", (F.col("n1") * F.col("n2")).alias("pairs")))
    return places.select("level", F.lit(0).cast("long").alias("pairs")).unionByName(inside).groupBy("level").agg(F.sum("pairs").alias("violations"))


def viewport_density(marks: DataFrame, wv: float, hv: float) -> DataFrame:
    """(level, most): most marks in a half-open window whose left and lower side each touch a mark.

    No window holds more than such a one.  Each mark meets those to its right within a window's width and
    above or below within its height, through cells of that size; along their heights a running count
    tells how many lie in the window that begins at each.
    """
    cell = lambda c, s: F.floor(F.col(c) / s)
    base = marks.select("level", "cluster_id", "cx", "cy").withColumn("a", cell("cx", wv)).withColumn("b", cell("cy", hv))
    left = base.select("level", F.col("cluster_id").alias("left"), F.col("cx").alias("x0"), F.col("cy").alias("yl"), "a", "b")
    left = left.withColumn("da", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("db", F.explode(F.array(*(F.lit(k) for k in (-1, 0, 1)))))
    left = left.select("level", "left", "x0", "yl", (F.col("a") + F.col("da")).alias("a"), (F.col("b") + F.col("db")).alias("b"))
    beside = (F.col("cx") >= F.col("x0")) & (F.col("cx") < F.col("x0") + wv) & (F.col("cy") > F.col("yl") - hv) & (F.col("cy") < F.col("yl") + hv)
    met = left.join(base.select("level", "cx", "cy", "a", "b"), ["level", "a", "b"]).where(beside).select("level", "left", "yl", "cy")
    up = f"count(1) OVER (PARTITION BY level, `left` ORDER BY cy RANGE BETWEEN {{}} AND {float(hv)!r}D FOLLOWING)"
    # the upper side doesn't belong to the window
    n = F.expr(up.format("CURRENT ROW")) - F.expr(up.format(f"{float(hv)!r}D FOLLOWING"))
    return met.withColumn("n", n).where("cy <= yl").groupBy("level").agg(F.max("n").alias("most"))


def fullness(marks: DataFrame, plan: LayoutPlan) -> DataFrame:
    """(level, marks, capacity, share, occupied): share of the capacity, and of the cells of theta that hold a mark."""
    w, h = plan.box[0] * plan.theta, plan.box[1] * plan.theta
    size = lambda k: F.lit(plan.top[k]) * F.pow(F.lit(float(plan.zoom)), F.col("level") - 1)
    capacity = (F.floor(size(0) / w) + 1) * (F.floor(size(1) / h) + 1)
    n = marks.groupBy("level").agg(F.count(F.lit(1)).alias("marks"), F.countDistinct(F.floor(F.col("cx") / w), F.floor(F.col("cy") / h)).alias("cells"))
    return n.select("level", "marks", capacity.alias("capacity"), (F.col("marks") / capacity).alias("share"), (F.col("cells") / capacity).alias("occupied"))


def zoom_violations(visible: DataFrame, levels: int) -> DataFrame:
    """(level, cluster_id) visible on a level but not on the next one below."""
    below = visible.select((F.col("level") - 1).alias("level"), "cluster_id")
    return visible.where(F.col("level") < levels).join(below, ["level", "cluster_id"], "left_anti")


def within_cluster_variation(layout: Layout, level: int) -> DataFrame:
    """(level, variation): mean pixel distance of objects from the mark that stands for them."""
    p = layout.plan
    place = lambda a: (G.to_level(F.col(f"{a}x"), *p.x_extent, p.top[0], p.zoom, level), G.to_level(F.col(f"{a}y"), *p.y_extent, p.top[1], p.zoom, level))
    own = layout.objects.select("obj_id", F.col("x").alias("ox"), F.col("y").alias("oy"))
    mark = layout.objects.select(F.col("obj_id").alias("cluster_id"), F.col("x").alias("mx"), F.col("y").alias("my"))
    (ox, oy), (mx, my) = place("o"), place("m")
    d = F.sqrt((ox - mx) * (ox - mx) + (oy - my) * (oy - my))
    joined = layout.members(level).join(own, "obj_id").join(mark, "cluster_id")
    return joined.agg(F.avg(d).alias("variation")).select(F.lit(level).alias("level"), "variation")


def percent_ranks(objects: DataFrame) -> DataFrame:
    """(cluster_id, p): the share of the other objects that are less important, in as many tasks as there are ranges of z.

    Equal values have one rank; only how many rows a range has goes to the driver.
    """
    values = objects.groupBy("z").agg(F.count(F.lit(1)).alias("n"))
    dealt = materialize(values.repartitionByRange(F.col("z").asc_nulls_first()).withColumn("part", F.spark_partition_id()), "ranks")
    sizes = sorted((r["part"], r["n"]) for r in dealt.groupBy("part").agg(F.sum("n").alias("n")).collect())
    starts, total = [], 0
    for part, n in sizes:
        starts.append((part, total))
        total += n
    before = W.partitionBy("part").orderBy(F.col("z").asc_nulls_first()).rowsBetween(W.unboundedPreceding, -1)
    base = objects.sparkSession.createDataFrame(starts, "part int, base long")
    below = F.coalesce(F.sum("n").over(before), F.lit(0))
    ranks = dealt.withColumn("below", below).join(F.broadcast(base), "part").select("z", ((F.col("below") + F.col("base")) / F.lit(float(max(total - 1, 1)))).alias("p"))
    named = ranks.withColumnRenamed("z", "rz")
    return objects.select(F.col("obj_id").alias("cluster_id"), "z").join(named, F.col("z").eqNullSafe(F.col("rz"))).select("cluster_id", "p")


def importance_by_level(visible: DataFrame, objects: DataFrame, top_share: float = 0.1, ranked: DataFrame | None = None) -> DataFrame:
    """(level, mean_rank, top_visible): mean percentile of the visible objects' importance (1 best), and the
    share of the most important objects that is visible.  ranked: percent_ranks of the objects, if they are known."""
    ranked = percent_ranks(objects) if ranked is None else ranked
    top = F.col("p") >= 1 - top_share
    best = ranked.agg(F.sum(top.cast("long")).alias("best"))
    out = visible.join(ranked, "cluster_id").groupBy("level").agg(F.avg("p").alias("mean_rank"), F.sum(top.cast("long")).alias("seen"))
    return out.crossJoin(F.broadcast(best)).select("level", "mean_rank", (F.col("seen") / F.col("best")).alias("top_visible"))


def quality(layout: Layout, ranked: DataFrame | None = None) -> DataFrame:
    """(level, marks, violations, most, occupied, mean_rank): the measures of a layout's marks side by side.

    ranked: percent_ranks of the layout's objects; layouts of the same objects can share them.
    """
    p = layout.plan
    marks = materialize(layout.marks(), "marks")
    full = fullness(marks, p).select("level", "marks", "occupied")
    clash = overlap_violations(marks, *p.box, p.theta)
    dense = viewport_density(marks, *p.top)
    important = importance_by_level(marks.select("level", "cluster_id"), layout.objects, ranked=ranked).select("level", "mean_rank")
    return full.join(clash, "level").join(dense, "level").join(important, "level")


def mass_conservation(states: DataFrame) -> DataFrame:
    """(level, objects): the counts of a level add up to the number of objects."""
    return states.groupBy("level").agg(F.sum("n").alias("objects"))


def partition_skew(assigned: DataFrame) -> DataFrame:
    sizes = assigned.groupBy("pid").count()
    return sizes.agg(F.count(F.lit(1)).alias("leaves"), F.max("count").alias("largest"), F.avg("count").alias("mean"), (F.max("count") / F.avg("count")).alias("skew"))


def isolated(rows: DataFrame, wb: float, hb: float, theta: float) -> DataFrame:
    """Objects of a level (level, cluster_id, cx, cy) with no other closer than theta.

    Decided by places: what shares one, and what lies in a cell less than theta across, has another nearby.  Only
    the other places, few in a cell, are compared with those around them.
    """
    if theta <= 0:
        return rows
    w, h = wb * theta, hb * theta
    d = lambda *c: G.ncd(*(F.col(k) for k in c), wb, hb)
    places = rows.where("cx IS NOT NULL AND cy IS NOT NULL").groupBy("level", "cx", "cy").agg(F.min("cluster_id").alias("lo"), F.max("cluster_id").alias("hi"))
    places = places.withColumn("a", F.floor(F.col("cx") / w)).withColumn("b", F.floor(F.col("cy") / h))
    cells = places.groupBy("level", "a", "b").agg(*(f(c).alias(f"{k}{c}") for k, f in (("l", F.min), ("h", F.max)) for c in ("cx", "cy")), F.min("lo").alias("first"), F.max("hi").alias("last"))
    tight = cells.where((F.col("first") < F.col("last")) & (d("lcx", "lcy", "hcx", "hcy") < theta)).select("level", "a", "b")
    crowded = (F.col("lo") < F.col("hi")) & (d("cx", "cy", "cx", "cy") < theta)
    open_ = places.join(tight.hint("merge"), ["level", "a", "b"], "left_anti").where(~crowded)
    steps = F.array(*(F.lit(k) for k in (-1, 0, 1)))
    spread = open_.select("level", "cx", "cy", "lo", "a", "b").withColumn("da", F.explode(steps)).withColumn("db", F.explode(steps))
    spread = spread.select("level", F.col("cx").alias("x1"), F.col("cy").alias("y1"), F.col("lo").alias("id1"), (F.col("a") + F.col("da")).alias("a"), (F.col("b") + F.col("db")).alias("b"))
    other = (F.col("lo") != F.col("id1")) | (F.col("hi") != F.col("id1"))
    met = spread.join(places.hint("merge"), ["level", "a", "b"]).where(other & (d("x1", "y1", "cx", "cy") < theta))
    parts = [places.join(tight.hint("merge"), ["level", "a", "b"], "left_semi").select("level", "cx", "cy"), places.where(crowded).select("level", "cx", "cy"), met.select("level", F.col("x1").alias("cx"), F.col("y1").alias("cy"))]
    near = parts[0].unionByName(parts[1]).unionByName(parts[2]).distinct()
    return rows.join(near.hint("merge"), ["level", "cx", "cy"], "left_anti").select(*rows.columns)


def provision_of(sizes: DataFrame, most: int = 2_000_000, per_node: int = 8) -> DataFrame:
    """sizes(objects, ...) with partitions and nodes, as `provision` has them."""
    parts = F.ceil(F.col("objects") / most)
    return sizes.withColumn("partitions", parts.cast("long")).withColumn("nodes", F.ceil(parts / per_node).cast("long"))


def provision(objects: int, most: int = 2_000_000, per_node: int = 8) -> tuple[int, int]:
    """(partitions, nodes)."""
    parts = math.ceil(objects / most)
    return parts, math.ceil(parts / per_node)
