"""Relational operators, functions and serving around the layouts."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions import geometry as G
from ..functions.sql import register_functions
from ..operators import kdtree
from ..operators import layout as L
from ..plans.materialize import fresh_path
from ..sources.fixtures import CUSTOMER, EVENTS, ORDERS, PIE, SUPPLIER, register, table
from ..sources.index import ServingSession, Viewport, fetch, linked_fetch, write_index
from .layout_queries import greedy_sql

VIEW = (6000.0, 500.0, 9000.0, 3000.0)


def viewport_fetch(spark, d):
    return EVENTS.pixels(spark, d, 4).where(G.viewport_predicate(*VIEW, 100.0, 100.0)).select("obj_id")


def _stored(spark, d, fixture=EVENTS, levels=4):
    """The stored index of a layout in which nothing merges, so that SQL has the same marks."""
    plan = fixture.plan(theta=0.0, levels=levels, mem_cap=500)
    return write_index(L.layout_distributed(fixture.objects(spark, d), plan, hybrid=False), fresh_path(spark, "index"))


def viewport_fetch_bbox(spark, d):
    """By the boxes themselves, which no reader can use."""
    return fetch(_stored(spark, d), Viewport(4, *VIEW), pushdown=False).select(F.col("cluster_id").alias("obj_id"))


def viewport_fetch_index(spark, d):
    return fetch(_stored(spark, d), Viewport(4, *VIEW)).select(F.col("cluster_id").alias("obj_id"))


def kd_prune(spark, d):
    """Half planes of the first split that a viewport meets, and what they hold."""
    rows = EVENTS.pixels(spark, d, 4)
    tree = kdtree.build_exact(EVENTS.objects(spark, d), 1, turns=1)
    lo, hi = EVENTS.x_extent
    raw = lambda px: px / 8000.0 * (hi - lo) + lo
    hit = tree.leaves_meeting(raw(VIEW[0] - 50), -1e18, raw(VIEW[2] + 50), 1e18)
    return L.assign_leaf(rows, tree).where(F.col("pid").isin(hit)).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


def visible_items(spark, d):
    session = ServingSession(_stored(spark, d), Viewport(4, *VIEW))
    return session.visible_items().agg(F.count(F.lit(1)).alias("items"))


def linked_view_semi(spark, d):
    """Marks of the orders' view that belong to customers picked in theirs."""
    picked = CUSTOMER.pixels(spark, d, 1).where("cx < 300").select(F.col("obj_id").alias("c"))
    ids = table(spark, d, "orders").join(picked, F.col("o_custkey") == F.col("c"), "left_semi").select(F.col("o_orderkey").alias("obj_id"))
    return linked_fetch(_stored(spark, d, ORDERS, 1), ids, 1).select(F.col("cluster_id").alias("o_orderkey"))


def linked_view_anti(spark, d):
    orders = table(spark, d, "orders").select("o_custkey")
    customers = table(spark, d, "customer").select("c_custkey", "c_nationkey")
    return customers.join(orders, customers["c_custkey"] == orders["o_custkey"], "left_anti").select("c_custkey", "c_nationkey")


def extent_clip(spark, d):
    return PIE.pixels(spark, d, 1).agg(F.count(F.lit(1)).alias("kept"), F.round(F.max("x"), 6).alias("largest"))


def domain_filter(spark, d):
    return table(spark, d, "events").where(F.col("event_type").isin("click", "view") & F.col("event_type").like("%i%")).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def null_drop(spark, d):
    rows = table(spark, d, "events").select("event_id", F.when(F.col("event_id") % 7 != 0, F.col("value")).alias("x"), F.try_divide(F.col("value"), F.col("event_id") % 3).alias("y"))
    return rows.where(F.col("x").isNotNull() & F.col("y").isNotNull() & ~F.isnan("x")).agg(F.count(F.lit(1)).alias("kept"), F.sum("event_id").alias("ids"))


def order_scatter_join(spark, d):
    orders, customer, nation, region = (table(spark, d, t) for t in ("orders", "customer", "nation", "region"))
    rows = orders.join(customer, orders["o_custkey"] == customer["c_custkey"]).join(nation, F.col("c_nationkey") == F.col("n_nationkey")).join(region, F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.groupBy("r_name", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def nation_dim_join(spark, d):
    supplier, nation = table(spark, d, "supplier"), table(spark, d, "nation")
    return supplier.join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))  # nation: 25 rows at any size


def doc_label_left(spark, d):
    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    return docs.join(labels, "doc_id", "left").groupBy(F.coalesce("quality", F.lit(-1)).cast("long").alias("quality")).agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


def domain_zero_fill(spark, d):
    """Every cell has a row for every event type."""
    rows = EVENTS.pixels(spark, d, 1, "event_type").withColumn("cell", F.floor(F.col("cy") / 100))
    state = rows.groupBy(F.col("cell").alias("cluster_id"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    from ..operators.rollup import zero_filled

    return zero_filled(state, "event_type", ["click", "error", "purchase", "signup", "view"]).select("cluster_id", "event_type", "n")


def level_diff_full(spark, d):
    a = ORDERS.pixels(spark, d, 1).where("cx < 400").select(F.col("obj_id").alias("a"))
    b = ORDERS.pixels(spark, d, 1).where("cy < 300").select(F.col("obj_id").alias("b"))
    side = F.when(F.col("b").isNull(), "left").when(F.col("a").isNull(), "right").otherwise("both")
    return a.join(b, F.col("a") == F.col("b"), "full").groupBy(side.alias("side")).agg(F.count(F.lit(1)).alias("n"))


def tile_lattice(spark, d):
    """Columns of tiles of three levels, empty ones too, and the events in each."""
    levels = spark.range(1, 4).select(F.col("id").alias("level"))
    lattice = levels.crossJoin(spark.range(0, 4).select(F.col("id").alias("tx"))).where("tx < pow(2, level - 1)").select("level", "tx")
    # the far side of the extent belongs to the last column
    bottom = EVENTS.pixels(spark, d, 3).groupBy(F.least(F.floor(F.col("cx") / 1000), F.lit(3)).cast("long").alias("t")).agg(F.count(F.lit(1)).alias("n"))
    up = F.floor(F.col("t") / F.pow(F.lit(2.0), 3 - F.col("level"))) == F.col("tx")
    return lattice.join(F.broadcast(bottom), up, "left").groupBy("level", "tx").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def interval_join_trace(spark, d):
    """Events inside three-hour windows that start every two days."""
    windows = spark.range(0, 15).select(F.col("id").alias("w"), (F.lit(1704067200.0) + F.col("id") * 172800).alias("lo"))
    events = EVENTS.objects(spark, d)
    # windows become cells of their own width, so that the join is one of equal keys
    cells = windows.withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / 10800), F.floor((F.col("lo") + 10800) / 10800))))
    return events.withColumn("cell", F.floor(F.col("x") / 10800)).join(cells, "cell").where("x >= lo and x < lo + 10800").groupBy("w").agg(F.count(F.lit(1)).alias("n"))


def asof_events(spark, d):
    """For each purchase the last click of the same user at or before it."""
    events = table(spark, d, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"), "value").where("event_type in ('click', 'purchase')")
    w = W.partitionBy("user_id").orderBy("ts", "event_type", "event_id").rowsBetween(W.unboundedPreceding, 0)
    click = F.when(F.col("event_type") == "click", F.unix_micros("ts"))
    return events.withColumn("last", F.last(click, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "last")


def nearest_kept(spark, d):
    """For each supplier that no mark of the top level stands for itself the nearest mark, within a box of 150."""
    rows = SUPPLIER.pixels(spark, d, 1)
    seen = L.layout_single(SUPPLIER.objects(spark, d), SUPPLIER.plan()).visible(1).select(F.col("cluster_id").alias("obj_id"))
    kept = rows.join(seen, "obj_id").select(F.col("obj_id").alias("k"), F.col("cx").alias("kx"), F.col("cy").alias("ky"))
    steps = F.array(*(F.lit(k) for k in (-1, 0, 1)))
    cells = kept.withColumn("a", F.floor(F.col("kx") / 150)).withColumn("b", F.floor(F.col("ky") / 150))
    near = rows.join(seen, "obj_id", "left_anti").withColumn("dx", F.explode(steps)).withColumn("dy", F.explode(steps))
    near = near.withColumn("a", F.floor(F.col("cx") / 150) + F.col("dx")).withColumn("b", F.floor(F.col("cy") / 150) + F.col("dy"))
    dist = G.ncd(F.col("cx"), F.col("cy"), F.col("kx"), F.col("ky"), 150.0, 150.0)
    return near.join(cells, ["a", "b"]).where(dist < 1).groupBy("obj_id").agg(F.min_by("k", F.struct(dist, F.col("k"))).alias("nearest"))


def approx_distinct(spark, d):
    """Distinct values by a sketch, whose error is below one half for so few values."""
    rows = table(spark, d, "lineitem")
    return rows.agg(F.approx_count_distinct("l_returnflag", 0.01).alias("flags"), F.approx_count_distinct("l_linestatus", 0.01).alias("states"))


def domain_values(spark, d):
    return table(spark, d, "lineitem").select("l_returnflag", "l_linestatus").distinct()


def distinct_xy(spark, d):
    rows = table(spark, d, "lineitem")
    return rows.agg(F.countDistinct("l_quantity").alias("quantities"), F.countDistinct("l_quantity", "l_returnflag").alias("pairs"), F.count_distinct("l_suppkey").alias("suppliers"))


_DIMS = ("l_returnflag", "l_linestatus")


def dims_cube(spark, d):
    return table(spark, d, "lineitem").cube(*_DIMS).agg(F.count(F.lit(1)).alias("n"))


def dims_rollup(spark, d):
    return table(spark, d, "lineitem").rollup(*_DIMS).agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"))


def dims_grouping_sets(spark, d):
    register(spark, d, ["lineitem"])
    return spark.sql("SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) AS BIGINT) AS g, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())")


def dims_pivot(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))


def measures_unpivot(spark, d):
    rows = table(spark, d, "supplier").groupBy("s_nationkey").agg(F.min("s_acctbal").alias("least"), F.max("s_acctbal").alias("most"))
    return rows.unpivot("s_nationkey", ["least", "most"], "measure", "value")


def importance_rank(spark, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    cols = [f().over(w).cast("long").alias(n) for f, n in ((F.row_number, "place"), (F.rank, "rank"), (F.dense_rank, "dense"))]
    return table(spark, d, "orders").select("o_orderkey", *cols, F.round(F.percent_rank().over(w), 6).alias("percent"), F.ntile(10).over(w).cast("long").alias("tenth"))


def sweep_neighbours(spark, d):
    """Rows in order along a split, with the one before and after, and those at the ends."""
    w = W.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    whole = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, d, "supplier").select(
        "s_suppkey", F.lag("s_suppkey").over(w).alias("before"), F.lead("s_suppkey").over(w).alias("after"), F.first_value("s_suppkey").over(whole).alias("first"),
        F.last_value("s_suppkey").over(whole).alias("last"), F.nth_value("s_suppkey", 2).over(whole).alias("second"),
    )


def moving_density(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 2)
    return table(spark, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("mean"))


def range_density(spark, d):
    w = W.partitionBy("s_nationkey").orderBy("s_acctbal").rangeBetween(-500, 500)
    return table(spark, d, "supplier").select("s_suppkey", F.count(F.lit(1)).over(w).alias("near"))


def topk_global(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


def fetch_page(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(10).select("o_orderkey")


def _windows(spark, d):
    rows = ORDERS.pixels(spark, d, 2)
    return rows.where("cx between 200 and 900").select("obj_id"), rows.where("cx between 600 and 1400").select("obj_id")


def fetch_union(spark, d):
    a, b = _windows(spark, d)
    return a.unionByName(b).distinct().agg(F.count(F.lit(1)).alias("n"), F.sum("obj_id").alias("ids"))


def visible_intersect(spark, d):
    a, b = _windows(spark, d)
    return a.intersect(b).agg(F.count(F.lit(1)).alias("n"), F.sum("obj_id").alias("ids"))


def visible_except(spark, d):
    """What a pan brings that was not there before."""
    a, b = _windows(spark, d)
    return b.subtract(a).agg(F.count(F.lit(1)).alias("n"), F.sum("obj_id").alias("ids"))


def scalar_extent(spark, d):
    register(spark, d, ["supplier"])
    return spark.sql("SELECT s_suppkey, round((s_acctbal - (SELECT min(s_acctbal) FROM supplier)) / ((SELECT max(s_acctbal) FROM supplier) - (SELECT min(s_acctbal) FROM supplier)), 9) AS u FROM supplier")


def exists_subquery(spark, d):
    register(spark, d, ["customer", "orders"])
    return spark.sql("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 450000) AND c_nationkey IN (SELECT c_nationkey FROM customer WHERE c_acctbal > 9900)")


def cte_levels(spark, d):
    """Ancestors up to the top of all tiles that hold an event, by recursion, and how many of these tiles each covers."""
    EVENTS.pixels(spark, d, 6).selectExpr("CAST(floor(cx / 500) AS INT) AS tx", "CAST(floor(cy / 500) AS INT) AS ty").distinct().createOrReplaceTempView("bottom_tiles")
    return spark.sql(
        "WITH RECURSIVE up(level, tx, ty) AS (SELECT 6, tx, ty FROM bottom_tiles UNION ALL SELECT level - 1, CAST(tx DIV 2 AS INT), CAST(ty DIV 2 AS INT) FROM up WHERE level > 1) "
        "SELECT level, tx, ty, count(*) AS tiles FROM up GROUP BY level, tx, ty"
    )


def string_funcs(spark, d):
    t = F.col("text")
    return table(spark, d, "benchmark").select(
        "item_id", F.length(t).cast("long").alias("n"), F.lower(F.substring(t, 1, 12)).alias("head"), F.size(F.split(t, " ")).cast("long").alias("words"),
        F.regexp_replace(F.substring(t, 1, 30), "[aeiou]", "*").alias("starred"), F.concat_ws("-", F.trim(F.substring(t, 1, 4)), F.lit("x")).alias("joined"), t.rlike("^[A-Z]").alias("capital"),
    )


def date_funcs(spark, d):
    ts = F.col("o_orderdate").cast("timestamp")
    rows = table(spark, d, "orders").select(F.date_trunc("month", ts).alias("m"), (F.dayofweek(ts) - 1).cast("long").alias("weekday"), F.hour(ts).alias("h"), F.datediff(ts, F.lit("1995-01-01").cast("date")).alias("days"), (ts + F.expr("make_interval(0, 0, 0, 1)")).alias("next"))
    return rows.groupBy(F.unix_seconds("m").alias("month"), "weekday").agg(F.count(F.lit(1)).alias("n"), F.sum("days").cast("long").alias("days"), F.max(F.unix_seconds("next")).alias("latest"), F.max("h").cast("long").alias("hour"))


def array_funcs(spark, d):
    e = F.transform("embedding", lambda x: F.round(x.cast("double"), 3))
    rows = table(spark, d, "embeddings").select("vec_id", F.slice(e, 1, 8).alias("a"))
    return rows.select(
        "vec_id", F.element_at("a", 2).alias("second"), F.size(F.filter("a", lambda x: x > 0)).cast("long").alias("positive"), F.round(F.aggregate("a", F.lit(0.0), lambda s, x: s + x), 6).alias("total"),
        F.element_at(F.array_sort("a"), 1).alias("least"), F.round(F.aggregate(F.zip_with("a", F.reverse("a"), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x), 6).alias("folded"), F.size(F.array_distinct(F.transform("a", lambda x: x > 0))).cast("long").alias("signs"),
    )


def map_funcs(spark, d):
    pairs = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    doubled = F.transform_values(F.map_filter("m", lambda k, v: v > 1), lambda k, v: v * 2)
    merged = F.map_zip_with("m", doubled, lambda k, a, b: a + F.coalesce(b, F.lit(0)))
    return pairs.select("user_id", F.explode(merged).alias("event_type", "n"))


def json_props(spark, d):
    rows = table(spark, d, "events").select(F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long").alias("s"))
    return rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.sum("s.k").alias("total"), F.max(F.to_json("s")).alias("text"))


def udtf_lattice(spark, d):
    """Windows that cover the values of each type of event, on the third level."""
    register_functions(spark)
    register(spark, d, ["events"])
    return spark.sql("SELECT event_type, level, x0, y0 FROM (SELECT event_type, max(value) AS height FROM events GROUP BY event_type) AS t, LATERAL viewport_lattice(3, 1000.0D, t.height, 800.0D)")


def sql_ncd(spark, d):
    register_functions(spark)
    SUPPLIER.pixels(spark, d, 1).createOrReplaceTempView("supplier_pixels")
    return spark.sql("SELECT obj_id, round(ncd(cx, cy, 500.0D, 500.0D, 100.0D, 50.0D), 9) AS d FROM supplier_pixels")


QUERIES = {
    f.__name__: f
    for f in (
        viewport_fetch, viewport_fetch_bbox, viewport_fetch_index, kd_prune, visible_items, linked_view_semi, linked_view_anti, extent_clip, domain_filter, null_drop, order_scatter_join,
        nation_dim_join, doc_label_left, domain_zero_fill, level_diff_full, tile_lattice, interval_join_trace, asof_events, nearest_kept, domain_values, approx_distinct, distinct_xy, dims_cube,
        dims_rollup, dims_grouping_sets, dims_pivot, measures_unpivot, importance_rank, sweep_neighbours, moving_density, range_density, topk_global, fetch_page, fetch_union,
        visible_intersect, visible_except, scalar_extent, exists_subquery, cte_levels, string_funcs, date_funcs, array_funcs, map_funcs, json_props, udtf_lattice, sql_ncd,
    )
}

_FETCH = f"SELECT obj_id FROM {EVENTS.pixels_sql(4)} WHERE cx BETWEEN 5950 AND 9050 AND cy BETWEEN 450 AND 3050"
_WINDOWS = f"WITH a AS (SELECT obj_id FROM {ORDERS.pixels_sql(2)} WHERE cx BETWEEN 200 AND 900), b AS (SELECT obj_id FROM {ORDERS.pixels_sql(2)} WHERE cx BETWEEN 600 AND 1400) SELECT count(*) AS n, CAST(sum(obj_id) AS BIGINT) AS ids FROM "
SQL = {
    "viewport_fetch": _FETCH, "viewport_fetch_bbox": _FETCH, "viewport_fetch_index": _FETCH,
    "kd_prune": f"WITH p AS (SELECT x FROM {EVENTS.pixels_sql(4)}), m AS (SELECT x AS v FROM {EVENTS.sql()} ORDER BY x LIMIT 1 OFFSET (SELECT count(*) // 2 FROM events)) SELECT CASE WHEN x < v THEN 0 ELSE 1 END AS pid, count(*) AS n FROM p, m WHERE CASE WHEN x < v THEN 1704067200 + 5950 / 8000.0 * 2592000 < v ELSE 1704067200 + 9050 / 8000.0 * 2592000 >= v END GROUP BY 1",
    "visible_items": f"SELECT count(*) AS items FROM ({_FETCH})",
    "linked_view_semi": f"SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT obj_id FROM {CUSTOMER.pixels_sql(1)} WHERE cx < 300)",
    "linked_view_anti": "SELECT c_custkey, c_nationkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    "extent_clip": f"SELECT count(*) AS kept, round(max(x), 6) AS largest FROM {PIE.pixels_sql(1)}",
    "domain_filter": "SELECT event_type, count(*) AS n FROM events WHERE event_type IN ('click', 'view') AND event_type LIKE '%i%' GROUP BY 1",
    "null_drop": "SELECT count(*) AS kept, CAST(sum(event_id) AS BIGINT) AS ids FROM events WHERE event_id % 7 <> 0 AND event_id % 3 <> 0",
    "order_scatter_join": "SELECT r_name, o_orderpriority, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
    "nation_dim_join": "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1",
    "doc_label_left": "SELECT CAST(coalesce(quality, -1) AS BIGINT) AS quality, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1",
    "domain_zero_fill": f"WITH s AS (SELECT CAST(floor(cy / 100) AS BIGINT) AS c, event_type AS e, count(*) AS n FROM {EVENTS.pixels_sql(1, 'event_type')} GROUP BY ALL) SELECT cluster_id, event_type, coalesce(n, 0) AS n FROM (SELECT DISTINCT c AS cluster_id FROM s) JOIN (VALUES ('click'), ('error'), ('purchase'), ('signup'), ('view')) AS t(event_type) ON true LEFT JOIN s ON c = cluster_id AND e = event_type",
    "level_diff_full": f"WITH a AS (SELECT obj_id AS a FROM {ORDERS.pixels_sql(1)} WHERE cx < 400), b AS (SELECT obj_id AS b FROM {ORDERS.pixels_sql(1)} WHERE cy < 300) SELECT CASE WHEN b IS NULL THEN 'left' WHEN a IS NULL THEN 'right' ELSE 'both' END AS side, count(*) AS n FROM a FULL JOIN b ON a = b GROUP BY 1",
    "tile_lattice": f"SELECT level, tx, count(t) AS n FROM range(1, 4) AS l(level) JOIN range(0, 4) AS r(tx) ON tx < pow(2, level - 1) LEFT JOIN (SELECT least(floor(cx / 1000), 3) AS t FROM {EVENTS.pixels_sql(3)}) ON floor(t / pow(2, 3 - level)) = tx GROUP BY 1, 2",
    "interval_join_trace": f"SELECT w, count(*) AS n FROM {EVENTS.sql()} JOIN (SELECT i AS w, 1704067200.0 + i * 172800 AS lo FROM range(0, 15) AS t(i)) ON x >= lo AND x < lo + 10800 GROUP BY w",
    "asof_events": "SELECT p.event_id, epoch_us(c.ts) AS last FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts",
    "nearest_kept": f"WITH p AS (SELECT * FROM {SUPPLIER.pixels_sql(1)}), s AS (SELECT child FROM ({greedy_sql(SUPPLIER, 6)}) WHERE level = 1 AND child = parent), q AS (SELECT a.obj_id, b.obj_id AS k, greatest(abs(a.cx - b.cx) / 150.0, abs(a.cy - b.cy) / 150.0) AS d FROM p a JOIN p b ON a.obj_id NOT IN (SELECT child FROM s) AND b.obj_id IN (SELECT child FROM s)) SELECT obj_id, arg_min(k, (d, k)) AS nearest FROM q WHERE d < 1 GROUP BY obj_id",
    "domain_values": "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem",
    "approx_distinct": "SELECT count(DISTINCT l_returnflag) AS flags, count(DISTINCT l_linestatus) AS states FROM lineitem",
    "distinct_xy": "SELECT count(DISTINCT l_quantity) AS quantities, count(DISTINCT (l_quantity, l_returnflag)) AS pairs, count(DISTINCT l_suppkey) AS suppliers FROM lineitem",
    "dims_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "dims_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "dims_grouping_sets": "SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) AS BIGINT) AS g, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())",
    "dims_pivot": "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY 1",
    "measures_unpivot": "SELECT s_nationkey, 'least' AS measure, min(s_acctbal) AS value FROM supplier GROUP BY 1 UNION ALL SELECT s_nationkey, 'most', max(s_acctbal) FROM supplier GROUP BY 1",
    "importance_rank": "SELECT * FROM (SELECT o_orderkey, row_number() OVER w AS place, rank() OVER w AS rank, dense_rank() OVER w AS dense, round(percent_rank() OVER w, 6) AS percent, ntile(10) OVER w AS tenth FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey))",
    "sweep_neighbours": "SELECT s_suppkey, lag(s_suppkey) OVER w AS before, lead(s_suppkey) OVER w AS after, first_value(s_suppkey) OVER f AS first, last_value(s_suppkey) OVER f AS last, nth_value(s_suppkey, 2) OVER f AS second FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey), f AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "moving_density": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS mean FROM events",
    "range_density": "SELECT s_suppkey, count(*) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS near FROM supplier",
    "topk_global": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "fetch_page": "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20",
    "fetch_union": _WINDOWS + "(SELECT * FROM a UNION SELECT * FROM b)", "visible_intersect": _WINDOWS + "(SELECT * FROM a INTERSECT SELECT * FROM b)", "visible_except": _WINDOWS + "(SELECT * FROM b EXCEPT SELECT * FROM a)",
    "scalar_extent": "SELECT s_suppkey, round((s_acctbal - (SELECT min(s_acctbal) FROM supplier)) / ((SELECT max(s_acctbal) FROM supplier) - (SELECT min(s_acctbal) FROM supplier)), 9) AS u FROM supplier",
    "exists_subquery": "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 450000) AND c_nationkey IN (SELECT c_nationkey FROM customer WHERE c_acctbal > 9900)",
    "cte_levels": f"WITH RECURSIVE up(level, tx, ty) AS (SELECT DISTINCT 6, CAST(floor(cx / 500) AS INTEGER), CAST(floor(cy / 500) AS INTEGER) FROM {EVENTS.pixels_sql(6)} UNION ALL SELECT level - 1, tx // 2, ty // 2 FROM up WHERE level > 1) SELECT level, tx, ty, count(*) AS tiles FROM up GROUP BY level, tx, ty",
    "string_funcs": "SELECT item_id, length(text) AS n, lower(substring(text, 1, 12)) AS head, CAST(len(string_split(text, ' ')) AS BIGINT) AS words, regexp_replace(substring(text, 1, 30), '[aeiou]', '*', 'g') AS starred, concat_ws('-', trim(substring(text, 1, 4)), 'x') AS joined, regexp_matches(text, '^[A-Z]') AS capital FROM benchmark",
    "date_funcs": "SELECT CAST(epoch(date_trunc('month', o_orderdate)) AS BIGINT) AS month, dayofweek(o_orderdate) AS weekday, count(*) AS n, CAST(sum(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))) AS BIGINT) AS days, CAST(max(epoch(o_orderdate + INTERVAL 1 DAY)) AS BIGINT) AS latest, max(hour(o_orderdate)) AS hour FROM orders GROUP BY 1, 2",
    "array_funcs": "WITH r AS (SELECT vec_id, list_transform(embedding[1:8], lambda x: round(x::DOUBLE, 3)) AS a FROM embeddings) SELECT vec_id, a[2] AS second, CAST(len(list_filter(a, lambda x: x > 0)) AS BIGINT) AS positive, round(list_sum(a), 6) AS total, list_min(a) AS least, round(list_sum(list_transform(range(1, 9), lambda i: a[i] * a[9 - i])), 6) AS folded, CAST(len(list_distinct(list_transform(a, lambda x: x > 0))) AS BIGINT) AS signs FROM r",
    "map_funcs": "SELECT user_id, event_type, CASE WHEN n > 1 THEN 3 * n ELSE n END AS n FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL)",
    "json_props": "SELECT k, count(*) AS n, CAST(sum(k) AS BIGINT) AS total, '{\"k\":' || k || '}' AS text FROM (SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events) GROUP BY k",
    "udtf_lattice": "SELECT event_type, 3 AS level, a * 800.0::DOUBLE AS x0, b * 800.0::DOUBLE AS y0 FROM (SELECT event_type, max(value) AS height FROM events GROUP BY 1), range(0, 5) AS s(a), range(0, 100) AS t(b) WHERE b < ceil(height * 4 / 800)",
    "sql_ncd": f"SELECT obj_id, round(greatest(abs(cx - 500) / 100.0, abs(cy - 500) / 50.0), 9) AS d FROM {SUPPLIER.pixels_sql(1)}",
}
