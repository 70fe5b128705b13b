"""Ways without a layout generator, for comparison."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def binned_aggregate(points: DataFrame, width: float, height: float) -> DataFrame:
    """points(cx, cy) to (bx, by, n, mx, my): counts and mean places of bins."""
    bins = points.groupBy(F.floor(F.col("cx") / width).alias("bx"), F.floor(F.col("cy") / height).alias("by"))
    return bins.agg(F.count(F.lit(1)).alias("n"), F.avg("cx").alias("mx"), F.avg("cy").alias("my"))


def sample_levels(points: DataFrame, levels: int, factor: int = 4) -> DataFrame:
    """(level, obj_id, ...): on the bottom level all, on each level above one of `factor`, by the id; nested."""
    depth = F.sequence(F.lit(1), F.lit(levels))
    rows = points.withColumn("level", F.explode(depth))
    return rows.where(F.col("obj_id") % F.pow(F.lit(float(factor)), F.lit(levels) - F.col("level")).cast("long") == 0)


def jitter(points: DataFrame, amount: float) -> DataFrame:
    """Places moved by up to amount, by the id, so that reruns agree."""
    part = lambda k: (F.col("obj_id") * k % 1009) / 1008.0 - 0.5
    return points.withColumn("cx", F.col("cx") + part(7919) * 2 * amount).withColumn("cy", F.col("cy") + part(104729) * 2 * amount)


def cell_topk(points: DataFrame, width: float, height: float, k: int) -> DataFrame:
    """The k most important objects of each cell; overlap is not looked at."""
    cell = W.partitionBy(F.floor(F.col("cx") / width), F.floor(F.col("cy") / height)).orderBy(F.desc("z"), "obj_id")
    return points.withColumn("place", F.row_number().over(cell)).where(F.col("place") <= k)


def grid_partition(points: DataFrame, columns: int, rows: int, width: float, height: float) -> DataFrame:
    """pid by a uniform grid over the canvas."""
    gx = F.least(F.floor(F.col("cx") / (width / columns)), F.lit(columns - 1))
    gy = F.least(F.floor(F.col("cy") / (height / rows)), F.lit(rows - 1))
    return points.withColumn("pid", (gx + gy * columns).cast("int"))


def tile_pyramid(points: DataFrame, levels: int, tile: float) -> DataFrame:
    """(level, tx, ty, n): counts of tiles, each level from the one below."""
    current = points.groupBy(F.floor(F.col("cx") / tile).alias("tx"), F.floor(F.col("cy") / tile).alias("ty")).agg(F.count(F.lit(1)).alias("n"))
    out = current.withColumn("level", F.lit(levels))
    for level in range(levels - 1, 0, -1):
        current = current.groupBy(F.floor(F.col("tx") / 2).alias("tx"), F.floor(F.col("ty") / 2).alias("ty")).agg(F.sum("n").alias("n"))
        out = out.unionByName(current.withColumn("level", F.lit(level)))
    return out.select("level", "tx", "ty", "n")
