"""Density marks: kernel sums on a grid, and contour lines through it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Line pieces by the case of a cell: bit 0 lower left, 1 lower right, 2 upper right, 3 upper left above
#: the threshold; sides: 0 low, 1 right, 2 high, 3 left.
SEGMENTS = {1: ((3, 0),), 2: ((0, 1),), 3: ((3, 1),), 4: ((1, 2),), 5: ((3, 2), (0, 1)), 6: ((0, 2),), 7: ((3, 2),), 8: ((2, 3),), 9: ((2, 0),), 10: ((3, 0), (1, 2)), 11: ((2, 1),), 12: ((1, 3),), 13: ((1, 0),), 14: ((0, 3),)}


def quartic(distance2: Column) -> Column:
    """Kernel of the squared distance in bandwidths; zero from one bandwidth on."""
    return F.when(distance2 < 1, (1 - distance2) * (1 - distance2)).otherwise(0.0)


def heatmap(points: DataFrame, cell: float, bandwidth: float, weight: Column | None = None) -> DataFrame:
    """points(cx, cy) to (gx, gy, density): the kernels' sum at the middle of each cell they reach."""
    reach = int(bandwidth // cell) + 1
    steps = F.sequence(F.lit(-reach), F.lit(reach))
    rows = points.select("cx", "cy", (F.lit(1.0) if weight is None else weight.cast("double")).alias("w"))
    rows = rows.withColumn("gx", F.explode(F.transform(steps, lambda k: F.floor(F.col("cx") / cell) + k)))
    rows = rows.withColumn("gy", F.explode(F.transform(steps, lambda k: F.floor(F.col("cy") / cell) + k)))
    dx, dy = (F.col("gx") + 0.5) * cell - F.col("cx"), (F.col("gy") + 0.5) * cell - F.col("cy")
    value = F.col("w") * quartic((dx * dx + dy * dy) / (bandwidth * bandwidth))
    return rows.select("gx", "gy", value.alias("d")).where("d > 0").groupBy("gx", "gy").agg(F.sum("d").alias("density"))


def thresholds(density: DataFrame, bands: int) -> list[float]:
    """Equal steps up to the greatest density."""
    top = density.agg(F.max("density")).first()[0] or 0.0
    return [top * k / bands for k in range(1, bands)]


def cell_cases(density: DataFrame, threshold: float) -> DataFrame:
    """(gx, gy, case, four corner values) of grid cells; what is missing counts as zero."""
    corners = density.withColumn("dx", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("dy", F.explode(F.array(F.lit(0), F.lit(1))))
    placed = corners.select((F.col("gx") - F.col("dx")).alias("gx"), (F.col("gy") - F.col("dy")).alias("gy"), (F.col("dx") + 2 * F.col("dy")).alias("c"), "density")
    at = lambda c: F.coalesce(F.max(F.when(F.col("c") == c, F.col("density"))), F.lit(0.0))
    cells = placed.groupBy("gx", "gy").agg(at(0).alias("ll"), at(1).alias("lr"), at(2).alias("ul"), at(3).alias("ur"))
    bit = lambda c, v: F.when(F.col(c) >= threshold, v).otherwise(0)
    return cells.withColumn("case", bit("ll", 1) + bit("lr", 2) + bit("ur", 4) + bit("ul", 8))


def contours(density: DataFrame, levels: list[float], cell: float) -> DataFrame:
    """(threshold, x0, y0, x1, y1): line pieces between cell middles, placed by linear interpolation."""
    out = None
    for t in levels:
        cells = cell_cases(density, t).where("case not in (0, 15)")
        cut = lambda a, b: F.coalesce(F.try_divide(F.lit(t) - F.col(a), F.col(b) - F.col(a)), F.lit(0.5))  # noqa: E731, B023
        x, y = (F.col("gx") + 0.5) * cell, (F.col("gy") + 0.5) * cell
        sides = F.array(
            F.struct((x + cut("ll", "lr") * cell).alias("x"), y.alias("y")),
            F.struct((x + cell).alias("x"), (y + cut("lr", "ur") * cell).alias("y")),
            F.struct((x + cut("ul", "ur") * cell).alias("x"), (y + cell).alias("y")),
            F.struct(x.alias("x"), (y + cut("ll", "ul") * cell).alias("y")),
        ).cast("array<struct<x:double,y:double>>")
        pieces = F.lit(None).cast("array<array<int>>")
        for case, lines in SEGMENTS.items():
            pieces = F.when(F.col("case") == case, F.array(*(F.array(*(F.lit(s) for s in line)) for line in lines))).otherwise(pieces)
        rows = cells.select(sides.alias("s"), F.explode(pieces).alias("p"))
        end = lambda k: F.element_at("s", F.col("p")[k] + 1)
        part = rows.select(F.lit(float(t)).alias("threshold"), end(0)["x"].alias("x0"), end(0)["y"].alias("y0"), end(1)["x"].alias("x1"), end(1)["y"].alias("y1"))
        out = part if out is None else out.unionByName(part)
    return out


def kde_importance(objects: DataFrame, cell: float, bandwidth: float) -> DataFrame:
    """objects(obj_id, cx, cy) with z: the more isolated, the larger (minus the density of the own cell)."""
    grid = heatmap(objects, cell, bandwidth)
    own = objects.withColumn("gx", F.floor(F.col("cx") / cell)).withColumn("gy", F.floor(F.col("cy") / cell))
    return own.join(grid, ["gx", "gy"], "left").withColumn("z", -F.coalesce("density", F.lit(0.0))).drop("gx", "gy", "density")
