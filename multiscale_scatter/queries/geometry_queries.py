"""Distance, density and pixel space."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators import kde
from ..operators.measures import close_pairs, isolated
from ..sources.fixtures import CUSTOMER, EVENTS, ORDERS, PART, SUPPLIER, table

#: (viewport width, height, box width, height, cap) with known thetas
DENSITY_CASES = [(1000, 1000, 100, 100, 100), (1000, 1000, 50, 50, 100), (1000, 1000, 100, 100, 50), (1000, 1000, 100, 100, 1000), (800, 600, 40, 30, 200), (1000, 600, 160, 130, 30)]
#: A part's mark: its box grows with the part's size, a viewport shows so many of them at most.
_BOX = {"wb": "40 + 4 * p_size", "hb": "30 + 2 * p_size", "cap": "1 + p_partkey % 200"}
_CASES_SQL = "(SELECT p_partkey, " + ", ".join(f"CAST({v} AS BIGINT) AS {k}" for k, v in _BOX.items()) + ", 1000 AS wv, 600 AS hv FROM part) AS t"


def ncd_pairs(spark, d):
    marks = CUSTOMER.pixels(spark, d, 4).withColumns({"level": F.lit(4), "cluster_id": F.col("obj_id")})
    return close_pairs(marks, 100.0, 100.0, 1.0).select("id1", "id2", F.round("d", 6).alias("d"))


def _near_and_all(spark, d, fixture, level, wb, hb, theta):
    """(pairs closer than theta with both places, number of all pairs): what is farther need not be looked at."""
    marks = fixture.pixels(spark, d, level).withColumns({"level": F.lit(level), "cluster_id": F.col("obj_id")})
    pairs = close_pairs(marks, wb, hb, theta).select("id1", "id2", "d")
    for k in (1, 2):
        pairs = pairs.join(marks.select(F.col("obj_id").alias(f"id{k}"), F.col("cx").alias(f"x{k}"), F.col("cy").alias(f"y{k}")), f"id{k}")
    n = marks.agg((F.count(F.lit(1)) * (F.count(F.lit(1)) - 1) / 2).cast("long").alias("all"))
    return pairs, n


def overlap_classes(spark, d):
    pairs, n = _near_and_all(spark, d, SUPPLIER, 2, 100.0, 100.0, 1.0)
    kinds = pairs.groupBy(G.overlap_kind(F.col("d")).alias("kind")).agg(F.count(F.lit(1)).alias("pairs"))
    rest = n.crossJoin(F.broadcast(pairs.agg(F.count(F.lit(1)).alias("near")))).select(F.lit("none").alias("kind"), (F.col("all") - F.col("near")).alias("pairs"))
    return kinds.unionByName(rest).where("pairs > 0")


def scaled_box_equiv(spark, d):
    """Boxes scaled by theta are disjoint just where the distance is theta at least; beyond twice theta both hold."""
    pairs, n = _near_and_all(spark, d, SUPPLIER, 2, 128.0, 64.0, 1.0)
    apart = G.scaled_boxes_disjoint(*(F.col(c) for c in ("x1", "y1", "x2", "y2")), 128.0, 64.0, 0.5)
    seen = pairs.groupBy(apart.alias("disjoint"), (F.col("d") >= 0.5).alias("far")).agg(F.count(F.lit(1)).alias("pairs"))
    rest = n.crossJoin(F.broadcast(pairs.agg(F.count(F.lit(1)).alias("near")))).select(F.lit(True).alias("disjoint"), F.lit(True).alias("far"), (F.col("all") - F.col("near")).alias("pairs"))
    return seen.unionByName(rest).groupBy("disjoint", "far").agg(F.sum("pairs").alias("pairs")).where("pairs > 0")


def viewport_capacity(spark, d):
    """Most marks of a viewport at the distance that each part's size asks for, in sixteenths of a box."""
    thetas = table(spark, d, "part").select("p_partkey", (F.col("p_size") / 16.0).alias("theta"))
    return thetas.select("p_partkey", "theta", G.viewport_capacity_col(F.col("theta"), 1000, 600, 160, 130).alias("capacity"))


def _part_thetas(spark, d):
    boxes = table(spark, d, "part").selectExpr("p_partkey", *(f"CAST({v} AS BIGINT) AS {k}" for k, v in _BOX.items()))
    return boxes.withColumn("theta", G.density_theta_col(F.lit(1000.0), F.lit(600.0), F.col("wb"), F.col("hb"), F.col("cap")))


def density_theta(spark, d):
    """Least distance of each part's marks so that a viewport of 1000 by 600 shows no more than its cap."""
    return _part_thetas(spark, d).select("p_partkey", "wb", "hb", "cap", F.round("theta", 9).alias("theta"))


def effective_theta(spark, d):
    """The same for three overlaps that a document may allow: the larger of the two distances holds."""
    rows = _part_thetas(spark, d).withColumn("overlap", F.explode(F.array(*(F.lit(o) for o in (0.0, 0.5, 1.0)))))
    return rows.select("p_partkey", "cap", "overlap", F.round(F.greatest("overlap", "theta"), 9).alias("theta"))


def pixel_projection(spark, d):
    return ORDERS.pixels(spark, d, 3).select("obj_id", F.round("cx", 6).alias("cx"), F.round("cy", 6).alias("cy"))


def isolated_objects(spark, d):
    rows = PART.pixels(spark, d, 6).withColumns({"level": F.lit(6), "cluster_id": F.col("obj_id")})
    return isolated(rows, 100.0, 100.0, 1.0).select("cluster_id")


def kde_importance(spark, d):
    out = kde.kde_importance(EVENTS.pixels(spark, d, 1).select("obj_id", "cx", "cy"), 20.0, 50.0)
    return out.select("obj_id", F.round("z", 6).alias("z"))


def math_geometry(spark, d):
    rows = SUPPLIER.pixels(spark, d, 1)
    angle = F.atan2(F.col("cy"), F.col("cx"))
    return rows.select("obj_id", F.round(F.sqrt(F.pow("cx", F.lit(2.0)) + F.pow("cy", F.lit(2.0))), 6).alias("radius"), F.round(F.sin(angle), 6).alias("s"), F.round(F.ln(F.col("cx") + 1), 6).alias("l"), F.pmod(F.floor("cx"), F.lit(7)).cast("long").alias("m"))


def morton_code(spark, d):
    rows = SUPPLIER.pixels(spark, d, 1)
    return rows.select("obj_id", G.morton(F.floor("cx"), F.floor("cy")).alias("code"))


QUERIES = {f.__name__: f for f in (ncd_pairs, overlap_classes, scaled_box_equiv, viewport_capacity, density_theta, effective_theta, pixel_projection, isolated_objects, kde_importance, math_geometry, morton_code)}

_NCD = "greatest(abs(a.cx - b.cx) / {w}, abs(a.cy - b.cy) / {h})"
_THETA = f"""SELECT *, (SELECT min(greatest(wv / (wb * a)::DOUBLE, hv / (hb * (cap // a))::DOUBLE))
  FROM range(1, 1001) AS r(a) WHERE a <= cap) AS best, greatest(wv / wb::DOUBLE, hv / hb::DOUBLE) AS whole FROM {_CASES_SQL}"""
SQL = {
    "ncd_pairs": f"SELECT a.obj_id AS id1, b.obj_id AS id2, round({_NCD.format(w=100.0, h=100.0)}, 6) AS d FROM {CUSTOMER.pixels_sql(4)} a JOIN {CUSTOMER.pixels_sql(4)} b ON a.obj_id < b.obj_id WHERE {_NCD.format(w=100.0, h=100.0)} < 1",
    "overlap_classes": f"SELECT CASE WHEN d >= 1 THEN 'none' WHEN d >= 0.5 THEN 'partial' ELSE 'heavy' END AS kind, count(*) AS pairs FROM (SELECT {_NCD.format(w=100.0, h=100.0)} AS d FROM {SUPPLIER.pixels_sql(2)} a JOIN {SUPPLIER.pixels_sql(2)} b ON a.obj_id < b.obj_id) GROUP BY 1",
    "scaled_box_equiv": f"""SELECT a.cx + 32.0 <= b.cx - 32.0 OR b.cx + 32.0 <= a.cx - 32.0 OR a.cy + 16.0 <= b.cy - 16.0 OR b.cy + 16.0 <= a.cy - 16.0 AS disjoint,
      {_NCD.format(w=128.0, h=64.0)} >= 0.5 AS far, count(*) AS pairs FROM {SUPPLIER.pixels_sql(2)} a JOIN {SUPPLIER.pixels_sql(2)} b ON a.obj_id < b.obj_id GROUP BY 1, 2""",
    "viewport_capacity": "SELECT p_partkey, i / 16.0::DOUBLE AS theta, CAST(ceil(1000.0::DOUBLE / (160.0 * (i / 16.0::DOUBLE))) * ceil(600.0::DOUBLE / (130.0 * (i / 16.0::DOUBLE))) AS BIGINT) AS capacity FROM (SELECT p_partkey, p_size AS i FROM part)",
    "density_theta": f"SELECT p_partkey, wb, hb, cap, round(least(best, whole), 9) AS theta FROM ({_THETA})",
    "effective_theta": f"SELECT p_partkey, cap, overlap, round(greatest(overlap, least(best, whole)), 9) AS theta FROM ({_THETA}), (VALUES (0.0::DOUBLE), (0.5), (1.0)) AS o(overlap)",
    "pixel_projection": f"SELECT obj_id, round(cx, 6) AS cx, round(cy, 6) AS cy FROM {ORDERS.pixels_sql(3)}",
    "isolated_objects": f"WITH p AS (SELECT * FROM {PART.pixels_sql(6)}) SELECT obj_id AS cluster_id FROM p a WHERE NOT EXISTS (SELECT 1 FROM p b WHERE a.obj_id <> b.obj_id AND {_NCD.format(w=100.0, h=100.0)} < 1)",
    "kde_importance": f"""WITH p AS (SELECT obj_id, cx, cy FROM {EVENTS.pixels_sql(1)}),
      s AS (SELECT floor(cx / 20.0) + i AS gx, floor(cy / 20.0) + j AS gy, cx, cy FROM p, range(-3, 4) AS a(i), range(-3, 4) AS b(j)),
      k AS (SELECT gx, gy, (((gx + 0.5) * 20.0 - cx) ** 2 + ((gy + 0.5) * 20.0 - cy) ** 2) / 2500.0 AS q FROM s),
      g AS (SELECT gx, gy, sum((1 - q) * (1 - q)) AS density FROM k WHERE q < 1 GROUP BY gx, gy)
      SELECT obj_id, round(-coalesce(density, 0.0), 6) AS z FROM p LEFT JOIN g ON floor(p.cx / 20.0) = g.gx AND floor(p.cy / 20.0) = g.gy""",
    "math_geometry": f"SELECT obj_id, round(sqrt(cx ** 2 + cy ** 2), 6) AS radius, round(sin(atan2(cy, cx)), 6) AS s, round(ln(cx + 1), 6) AS l, CAST(floor(cx) AS BIGINT) % 7 AS m FROM {SUPPLIER.pixels_sql(1)}",
    "morton_code": f"SELECT obj_id, CAST((SELECT sum((((CAST(floor(cx) AS BIGINT) >> i) & 1) << (2 * i)) + (((CAST(floor(cy) AS BIGINT) >> i) & 1) << (2 * i + 1))) FROM range(0, 16) AS t(i)) AS BIGINT) AS code FROM {SUPPLIER.pixels_sql(1)}",
}
