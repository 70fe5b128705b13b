"""Objects of the given tables: ids, places and importance, for Spark and for DuckDB."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators.layout import LayoutPlan

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
LINE_ID = "l_orderkey * 1000000000 + l_linenumber * 100000000 + CAST(round(l_extendedprice * 100) AS BIGINT)"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    """Temporary views of the tables, for data queries in SQL."""
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


@dataclass(frozen=True)
class Fixture:
    """Expressions that both engines understand; {s:...} and {d:...} differ where a time becomes a number."""

    table: str
    id: str
    x: str
    y: str
    z: str
    x_extent: tuple[float, float]
    y_extent: tuple[float, float]

    def _text(self, part: str, engine: str) -> str:
        text = getattr(self, part)
        for name in ("ts", "o_orderdate", "l_shipdate"):
            seconds = f"(unix_micros(CAST({name} AS TIMESTAMP)) / 1e6)" if engine == "spark" else f"(epoch_us({name}) / 1e6)"
            text = text.replace(f"@{name}", seconds)
        return text

    def objects(self, spark: SparkSession, sf_dir: str, *more: str) -> DataFrame:
        e = lambda p: self._text(p, "spark")
        rows = table(spark, sf_dir, self.table)
        return rows.selectExpr(f"CAST({e('id')} AS BIGINT) AS obj_id", f"CAST({e('x')} AS DOUBLE) AS x", f"CAST({e('y')} AS DOUBLE) AS y", f"CAST({e('z')} AS DOUBLE) AS z", *more)

    def sql(self, *more: str) -> str:
        e = lambda p: self._text(p, "duckdb")
        cols = [f"CAST({e('id')} AS BIGINT) AS obj_id", f"CAST({e('x')} AS DOUBLE) AS x", f"CAST({e('y')} AS DOUBLE) AS y", f"CAST({e('z')} AS DOUBLE) AS z", *more]
        return f"(SELECT {', '.join(cols)} FROM {self.table})"

    def plan(self, **changes) -> LayoutPlan:
        return LayoutPlan(self.x_extent, self.y_extent, **changes)

    def pixels(self, spark: SparkSession, sf_dir: str, level: int, *more: str) -> DataFrame:
        """obj_id, x, y, z, cx, cy inside the extents."""
        rows = self.objects(spark, sf_dir, *more).where(F.col("x").between(*self.x_extent) & F.col("y").between(*self.y_extent))
        return rows.withColumn("cx", G.to_level(F.col("x"), *self.x_extent, 1000.0, 2.0, level)).withColumn("cy", G.to_level(F.col("y"), *self.y_extent, 1000.0, 2.0, level))

    def pixels_sql(self, level: int, *more: str) -> str:
        (x0, x1), (y0, y1), size = self.x_extent, self.y_extent, 1000.0 * 2 ** (level - 1)
        return (
            f"(SELECT *, (x - {x0!r}::DOUBLE) / {float(x1 - x0)!r}::DOUBLE * {size!r}::DOUBLE AS cx, (y - {y0!r}::DOUBLE) / {float(y1 - y0)!r}::DOUBLE * {size!r}::DOUBLE AS cy "
            f"FROM {self.sql(*more)} WHERE x BETWEEN {x0!r} AND {x1!r} AND y BETWEEN {y0!r} AND {y1!r})"
        )


SUPPLIER = Fixture("supplier", "s_suppkey", "s_acctbal", "s_nationkey", "s_acctbal", (-1000.0, 10000.0), (-1.0, 25.0))
CUSTOMER = Fixture("customer", "c_custkey", "c_acctbal", "c_nationkey", "c_acctbal", (-1000.0, 10000.0), (-1.0, 25.0))
PART = Fixture("part", "p_partkey", "p_retailprice", "p_size", "p_retailprice", (900.0, 1000.0), (0.0, 51.0))
EVENTS = Fixture("events", "event_id", "@ts", "value", "value", (1704067200.0, 1706659200.0), (0.0, 600.0))
ORDERS = Fixture("orders", "o_orderkey", "@o_orderdate", "o_totalprice", "o_totalprice", (788918400.0, 996710400.0), (0.0, 500000.0))
LINEITEM = Fixture("lineitem", LINE_ID, "l_quantity", "l_extendedprice", "@l_shipdate", (0.0, 51.0), (0.0, 105000.0))
PIE = Fixture("lineitem", LINE_ID, "l_extendedprice / l_quantity", "l_quantity", "@l_shipdate", (0.0, 10000.0), (0.0, 51.0))


def skewed(spark: SparkSession, sf_dir: str, parts: int = 1) -> DataFrame:
    """Four fifths of the objects in the middle square of a fifth of the plane, the rest all over; one of `parts`."""
    rows = table(spark, sf_dir, "lineitem")
    top = rows.agg((F.max("l_suppkey") + 1).alias("s"), (F.max("l_partkey") + 1).alias("p"))
    u = (F.col("l_extendedprice") - 900) / 104100
    v = (F.col("l_partkey") + (F.col("l_suppkey") + 0.5) / F.col("s")) / F.col("p")
    hot = F.col("l_orderkey") % 5 != 0
    squeeze = lambda c: F.when(hot, 0.5 + (c - 0.5) * 0.2**0.5).otherwise(c)
    out = rows.crossJoin(F.broadcast(top)).select(F.expr(LINE_ID).cast("long").alias("obj_id"), squeeze(u).alias("x"), squeeze(v).alias("y"), F.col("l_extendedprice").alias("z"))
    return out if parts == 1 else out.where(F.col("obj_id") % parts == 0)
