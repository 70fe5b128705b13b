"""SQL functions and table functions for use in data queries."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

NCD = "CREATE OR REPLACE TEMPORARY FUNCTION ncd(px DOUBLE, py DOUBLE, qx DOUBLE, qy DOUBLE, wb DOUBLE, hb DOUBLE) RETURNS DOUBLE RETURN greatest(abs(px - qx) / wb, abs(py - qy) / hb)"


class Lattice:
    """Windows of a level: eval(level, width, height, window) yields the lower left corners."""

    def eval(self, level: int, width: float, height: float, window: float):
        full_w, full_h = width * 2 ** (level - 1), height * 2 ** (level - 1)
        for a in range(int(-(-full_w // window))):
            for b in range(int(-(-full_h // window))):
                yield level, a * window, b * window


def register_functions(spark: SparkSession) -> None:
    spark.sql(NCD)
    spark.udtf.register("viewport_lattice", udtf(Lattice, returnType="level int, x0 double, y0 double"))
