"""Streams of events: windows, late data, repeated ids, joins, and layouts that grow.

Every query reads the events as a stream of files until nothing is left and gives what the sink holds.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import kdtree
from ..operators import layout as L
from ..plans.materialize import fresh_path, materialize
from ..sources.fixtures import EVENTS, table


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with ts as a timestamp, the only kind that carries a watermark."""
    schema = table(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(f"{sf_dir}/events.parquet" if _is_folder(spark, sf_dir) else sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, sf_dir: str) -> bool:
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory()


def drained(stream: DataFrame, mode: str) -> DataFrame:
    """All that a query gives, once its input is used up, written as a table of the shared folder.

    What a complete query holds after a batch replaces what it held before; the driver sees none of its rows.
    """
    spark = stream.sparkSession
    path = fresh_path(spark, "sink")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream")).trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    written: list[str] = []

    def replace(batch: DataFrame, number: int) -> None:
        at = f"{path}/{number}"
        batch.write.mode("overwrite").parquet(at)
        written.append(at)

    writer.foreachBatch(replace).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(written[-1]) if written else spark.createDataFrame([], stream.schema)


def _start(c: str):
    return F.unix_seconds(F.col(c)).alias("start")


def stream_tumbling(spark, d):
    tile = F.floor(F.col("value") / 50).alias("tile")
    out = event_stream(spark, d).groupBy(F.window("ts", "6 hours").alias("w"), tile).agg(F.count(F.lit(1)).alias("n"))
    return drained(out, "complete").select(_start("w.start"), "tile", "n")


def stream_sliding(spark, d):
    out = event_stream(spark, d).groupBy(F.window("ts", "12 hours", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 3).alias("total"))
    return drained(out, "complete").select(_start("w.start"), "n", "total")


def stream_session(spark, d):
    out = event_stream(spark, d).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drained(out, "complete").select(_start("w.start"), "user_id", "n")


def stream_watermark(spark, d):
    """Hours that the watermark has passed; the last ones stay open."""
    out = event_stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    closed = table(spark, d, "events").agg((F.unix_seconds(F.max("ts").cast("timestamp")) - 7200).alias("last"))
    rows = drained(out, "append").select(_start("w.start"), "n")
    return rows.crossJoin(F.broadcast(closed)).where("start + 3600 <= last").select("start", "n")


def stream_dedup(spark, d):
    out = event_stream(spark, d).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return drained(out, "append")


def stream_kd_assign(spark, d):
    """Leaf of each event as it comes, by a tree over what is known."""
    rows = EVENTS.objects(spark, d)
    tree = kdtree.build_exact(rows, 1, turns=2)
    stream = event_stream(spark, d).select("event_id", (F.unix_micros("ts") / 1e6).alias("x"), F.col("value").alias("y"))
    return drained(L.assign_leaf(stream, tree).select("event_id", "pid"), "append").groupBy("pid").agg(F.count(F.lit(1)).alias("n"))


def stream_static_join(spark, d):
    names = table(spark, d, "nation").select("n_nationkey", "n_name")
    out = event_stream(spark, d).select("event_id", (F.col("user_id") % 25).cast("int").alias("k"))
    return drained(out.join(names, F.col("k") == F.col("n_nationkey")).select("event_id", "n_name"), "append").groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


def stream_interval(spark, d):
    """Clicks with a purchase of the same user within the next hour."""
    clicks = event_stream(spark, d).where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("click"), F.col("ts").alias("t")).withWatermark("t", "2 hours")
    buys = event_stream(spark, d).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), "ts").withWatermark("ts", "2 hours")
    both = clicks.join(buys, F.expr("u = user_id AND ts >= t AND ts <= t + INTERVAL 1 HOUR"))
    return drained(both.select("click", "purchase"), "append")


#: Days of a cell of stream_greedy, and how late an event may come.
CELL_DAYS, LATE = 10, "2 hours"


def stream_greedy(spark, d):
    """Marks of the stream as it comes: an event is one if no mark lies within a box of a day by 50; first come, first placed.

    The plane is cut into cells of ten days, each with the marks it has as its state.  Events within half a box of
    a cell's side wait for the next layout over all events, so marks of different cells never overlap.  The state
    is a grid of boxes, looked up by the nine around an event, and goes once the watermark has passed its cell.
    """
    day = F.unix_micros("ts") / 1e6 / 86400
    cells = event_stream(spark, d).select("event_id", "ts", day.alias("u"), (F.col("value") / 50).alias("v"), F.floor(day / CELL_DAYS).cast("long").alias("cell"))
    inside = (F.col("u") - F.col("cell") * CELL_DAYS >= 0.5) & ((F.col("cell") + 1) * CELL_DAYS - F.col("u") > 0.5)
    cells = cells.where(inside).withWatermark("ts", LATE)

    def place(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        marks: dict[tuple[int, int], list[tuple[float, float]]] = {}
        for u, v in zip(*state.get, strict=True) if state.exists else ():
            marks.setdefault((int(u // 1), int(v // 1)), []).append((u, v))
        new = []
        for pdf in batches:
            for i, u, v in pdf.sort_values("event_id")[["event_id", "u", "v"]].itertuples(index=False):
                a, b = int(u // 1), int(v // 1)
                near = (m for x in (a - 1, a, a + 1) for y in (b - 1, b, b + 1) for m in marks.get((x, y), ()))
                if all(max(abs(u - x), abs(v - y)) >= 1 for x, y in near):
                    marks.setdefault((a, b), []).append((float(u), float(v)))
                    new.append((key[0], int(i)))
        flat = [m for some in marks.values() for m in some]
        state.update(([m[0] for m in flat], [m[1] for m in flat]))
        state.setTimeoutTimestamp(max(int((key[0] + 1) * CELL_DAYS * 86_400_000), state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(new, columns=["cell", "event_id"])

    out = cells.groupBy("cell").applyInPandasWithState(place, "cell long, event_id long", "us array<double>, vs array<double>", "append", GroupStateTimeout.EventTimeTimeout)
    return drained(out, "append")


def grow_layout(stream: DataFrame, layout: L.Layout) -> list[L.Layout]:
    """Lays out again with each micro-batch, with the old tree while it fits.  The last is the current one."""
    layouts = [layout]

    def add(batch: DataFrame, _: int) -> None:
        layouts.append(L.relayout(layouts[-1], materialize(batch, "batch")))

    path = fresh_path(stream.sparkSession, "stream")
    stream.writeStream.foreachBatch(add).option("checkpointLocation", path).trigger(availableNow=True).start().awaitTermination()
    return layouts


def stream_relayout(spark, d):
    plan = EVENTS.plan(levels=3, mem_cap=500)
    old = L.layout_distributed(EVENTS.objects(spark, d).where("obj_id % 2 = 0"), plan)
    new = event_stream(spark, d).where("event_id % 2 = 1").select(F.col("event_id").alias("obj_id"), (F.unix_micros("ts") / 1e6).alias("x"), F.col("value").alias("y"), F.col("value").alias("z"))
    last = grow_layout(new, old)[-1]
    return last.objects.agg(F.count(F.lit(1)).alias("objects"))


QUERIES: dict[str, Callable] = {
    f.__name__: f for f in (stream_tumbling, stream_sliding, stream_session, stream_watermark, stream_dedup, stream_kd_assign, stream_static_join, stream_interval, stream_greedy, stream_relayout)
}
_GREEDY = """o AS (SELECT event_id, u, v, cell, row_number() OVER (ORDER BY event_id) AS r FROM (
    SELECT event_id, epoch_us(ts) / 1e6 / 86400 AS u, value / 50 AS v, CAST(floor(epoch_us(ts) / 1e6 / 86400 / 10) AS BIGINT) AS cell FROM events)
    WHERE u - cell * 10 >= 0.5 AND (cell + 1) * 10 - u > 0.5),
  g(r, cell, event_id, kept) AS (
    SELECT CAST(0 AS BIGINT), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT), CAST([] AS STRUCT(u DOUBLE, v DOUBLE)[])
    UNION ALL
    SELECT r, CASE WHEN free THEN cell END, CASE WHEN free THEN event_id END, CASE WHEN free THEN list_append(kept, {'u': u, 'v': v}) ELSE kept END
    FROM (SELECT o.r, o.cell, o.event_id, o.u, o.v, g.kept, NOT EXISTS (SELECT 1 FROM unnest(g.kept) AS q(k) WHERE greatest(abs(k.u - o.u), abs(k.v - o.v)) < 1) AS free
          FROM g JOIN o ON o.r = g.r + 1))"""
SQL = {
    "stream_greedy": f"WITH RECURSIVE {_GREEDY} SELECT cell, event_id FROM g WHERE event_id IS NOT NULL",
    "stream_tumbling": "SELECT CAST(floor(epoch_us(ts) / 1e6 / 21600) AS BIGINT) * 21600 AS start, CAST(floor(value / 50) AS BIGINT) AS tile, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT (CAST(floor(epoch_us(ts) / 1e6 / 21600) AS BIGINT) - i) * 21600 AS start, count(*) AS n, round(sum(value), 3) AS total FROM events, range(0, 2) AS t(i) GROUP BY 1",
    "stream_session": """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
      s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e) SELECT CAST(floor(epoch_us(min(ts)) / 1e6) AS BIGINT) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k""",
    "stream_watermark": "SELECT * FROM (SELECT CAST(floor(epoch_us(ts) / 1e6 / 3600) AS BIGINT) * 3600 AS start, count(*) AS n FROM events GROUP BY 1) WHERE start + 3600 <= (SELECT CAST(floor(epoch_us(max(ts)) / 1e6) AS BIGINT) - 7200 FROM events)",
    "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "stream_static_join": "SELECT n_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY 1",
    "stream_interval": "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR",
    "stream_relayout": f"SELECT count(*) AS objects FROM {EVENTS.pixels_sql(1)}",
}
