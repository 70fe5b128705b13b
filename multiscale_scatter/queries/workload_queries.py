"""The experiment workloads and their measures.  Layouts of their size are beyond SQL; the conserved totals are not."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import measures
from ..plans import workloads as W
from ..plans.spec import authoring_effort
from .layout_queries import greedy_sql_of


def _marks(spec):
    """Marks of all levels with all that a client draws of them."""

    def run(spark, d):
        return W.marks_with_payload(W.lay_out(spark, d, spec), spec)

    return run


def _contour(spec):
    """Contour lines of the three top levels, from the weighted marks."""

    def run(spark, d):
        layout = W.lay_out(spark, d, spec)
        parts = [W.contour_lines(layout, spec, level).select(F.lit(level).alias("level"), "*") for level in (1, 2, 3)]
        return parts[0].unionByName(parts[1]).unionByName(parts[2])

    return run


def wl_radar_embeddings(spark, d):
    rows = W.marks_with_payload(W.lay_out(spark, d, W.RADAR), W.RADAR)
    return rows.select("level", "cluster_id", F.round("cx", 4).alias("cx"), F.round("cy", 4).alias("cy"), "n", *(F.round(F.col("axes")[k], 5).alias(f"axis{k}") for k in range(8)), F.array_join("top", ",").alias("top"))


def wl_profile_customer(spark, d):
    rows = W.marks_with_payload(W.lay_out(spark, d, W.PROFILE), W.PROFILE)
    return rows.select("level", "cluster_id", F.round("cx", 4).alias("cx"), F.round("cy", 4).alias("cy"), "n", F.get_json_object("card", "$.c_name").alias("c_name"), F.get_json_object("card", "$.n_name").alias("n_name"))


def _mass(spec):
    def run(spark, d):
        return measures.mass_conservation(W.statistics(W.lay_out(spark, d, spec), spec)).select("level", "objects")

    return run


def wl_skew_lineitem(spark, d):
    return W._per_level(W.synthetic(spark, d, leaves=50))


def wl_skew_violations(spark, d):
    layout = W.synthetic(spark, d, leaves=50)
    return measures.overlap_violations(layout.marks(), *layout.plan.box, layout.plan.theta)


def wl_heatmap_density(spark, d):
    """Density grid of the top level of the heatmap."""
    layout = W.lay_out(spark, d, W.HEATMAP)
    return W.density_of_level(layout, W.HEATMAP, 1).agg(F.count(F.lit(1)).alias("cells"), F.round(F.sum("density"), 3).alias("mass"))


def authoring(spark, d):
    rows = []
    for name, spec in W.SPECS.items():
        e = authoring_effort(W.compiled(spark, d, spec))
        rows.append((name, e["lines"], e["low_lines"], e["tokens"], e["low_tokens"], e["line_ratio"], e["token_ratio"]))
    return spark.createDataFrame(rows, "spec string, lines long, low_lines long, tokens long, low_tokens long, line_ratio double, token_ratio double")


QUERIES = {f"wl_{name}": _contour(spec) if name.startswith("contour") else _marks(spec) for name, spec in W.SPECS.items()} | {
    "wl_circle_mass": _mass(W.CIRCLE), "wl_pie_mass": _mass(W.PIES), "wl_radar_mass": _mass(W.RADAR), "wl_radar_embeddings": wl_radar_embeddings, "wl_profile_customer": wl_profile_customer,
    "wl_skew_lineitem": wl_skew_lineitem, "wl_skew_violations": wl_skew_violations, "wl_heatmap_density": wl_heatmap_density, "authoring_effort": authoring,
}


def _members_sql(greedy: str, levels: int) -> str:
    """CTEs e (edges of all levels) and m (level, obj_id, cluster_id)."""
    ctes = [f"e AS ({greedy})", f"m{levels} AS (SELECT child AS obj_id, parent AS cluster_id FROM e WHERE level = {levels})"]
    ctes += [f"m{k} AS (SELECT obj_id, parent AS cluster_id FROM m{k + 1} JOIN e ON e.level = {k} AND e.child = m{k + 1}.cluster_id)" for k in range(levels - 1, 0, -1)]
    return ", ".join(ctes) + ", m AS (" + " UNION ALL ".join(f"SELECT {k} AS level, * FROM m{k}" for k in range(1, levels + 1)) + ")"


def _marks_sql(objects: str, x_extent: str, y_extent: str, box: tuple[float, float], theta: float, members: str, own: str, levels: int = 6) -> str:
    """Marks of a one-task layout of objects(obj_id, x, y, z, ...): members and own are aggregates and columns more."""
    greedy = greedy_sql_of(objects, x_extent, y_extent, levels, box, theta)
    (x0, x1), (y0, y1) = (tuple(part.strip() for part in e.split(";")) for e in (x_extent, y_extent))
    place = lambda c, lo, hi: f"round((o.{c} - {lo}) / ({hi} - {lo}) * 1000 * pow(2.0, a.level - 1), 4)"
    return f"""WITH o AS ({objects}), {_members_sql(greedy, levels)},
      a AS (SELECT level, cluster_id, count(*) AS n{members} FROM m JOIN o USING (obj_id) GROUP BY level, cluster_id)
      SELECT a.level, a.cluster_id, {place("x", x0, x1)} AS cx, {place("y", y0, y1)} AS cy, a.n{own} FROM a JOIN o ON o.obj_id = a.cluster_id"""


_RADAR_OBJECTS = "SELECT vec_id AS obj_id, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y, embedding[11]::DOUBLE AS z, embedding FROM embeddings WHERE embedding[1]::DOUBLE BETWEEN -0.5 AND 0.5 AND embedding[2]::DOUBLE BETWEEN -0.5 AND 0.5"
_PROFILE_OBJECTS = """SELECT c_custkey AS obj_id, c_acctbal::DOUBLE AS x, coalesce(total, 0.0)::DOUBLE AS y, coalesce(total, 0.0)::DOUBLE AS z, c_name, n_name FROM customer
  JOIN nation ON c_nationkey = n_nationkey LEFT JOIN (SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey) ON c_custkey = o_custkey"""
SQL = {
    "wl_circle_mass": "SELECT level, n AS objects FROM (SELECT count(*) AS n FROM events), range(1, 16) AS t(level)",
    "wl_pie_mass": "SELECT level, n AS objects FROM (SELECT count(*) AS n FROM lineitem), range(1, 9) AS t(level)",
    "wl_radar_mass": "SELECT level, n AS objects FROM (SELECT count(*) AS n FROM embeddings WHERE embedding[1]::DOUBLE BETWEEN -0.5 AND 0.5 AND embedding[2]::DOUBLE BETWEEN -0.5 AND 0.5), range(1, 7) AS t(level)",
    "wl_skew_violations": "SELECT level, CAST(0 AS BIGINT) AS violations FROM range(1, 9) AS t(level)",
    "wl_radar_embeddings": _marks_sql(
        _RADAR_OBJECTS, "(-0.5::DOUBLE); 0.5::DOUBLE", "(-0.5::DOUBLE); 0.5::DOUBLE", (80.0, 80.0), 1.0,
        "".join(f", round(least(greatest((avg(embedding[{k + 3}]::DOUBLE) + 0.5) / 1.0, 0.0), 1.0), 5) AS axis{k}" for k in range(8))
        + ", array_to_string(list_transform(list_sort(list({'w': -z, 'i': obj_id})), lambda q: q.i)[:3], ',') AS top",
        "".join(f", a.axis{k}" for k in range(8)) + ", a.top",
    ),
    "wl_profile_customer": _marks_sql(
        _PROFILE_OBJECTS, "(SELECT min(x) FROM o); (SELECT max(x) FROM o)", "(SELECT min(y) FROM o); (SELECT max(y) FROM o)", (160.0, 130.0), 0.5, "", ", o.c_name, o.n_name"
    ),
}
