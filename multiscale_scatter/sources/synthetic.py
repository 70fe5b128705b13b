"""A data source of skewed synthetic objects: four fifths in the middle fifth of the plane."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, first: int, end: int):
        self.first, self.end = first, end


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.rows = int(options.get("rows", 1000))
        self.parts = int(options.get("partitions", 8))
        self.seed = int(options.get("seed", 1))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.rows // self.parts)
        return [_Range(a, min(a + step, self.rows)) for a in range(0, self.rows, step)]

    def read(self, part: _Range) -> Iterator[pa.RecordBatch]:
        """Values follow from the id, so any partitioning gives the same objects."""
        for a in range(part.first, part.end, 65536):
            ids = np.arange(a, min(a + 65536, part.end), dtype=np.uint64)

            def unit(salt: int, ids: np.ndarray = ids) -> np.ndarray:
                h = (ids + np.uint64(salt * 1_000_003 + self.seed)) * np.uint64(0x9E3779B97F4A7C15)
                h ^= h >> np.uint64(31)
                h *= np.uint64(0xBF58476D1CE4E5B9)
                return ((h ^ (h >> np.uint64(29))) >> np.uint64(11)).astype(np.float64) / 2.0**53

            x, y, z = unit(1), unit(2), unit(3)
            hot = ids % np.uint64(5) != 0
            x[hot], y[hot] = (0.5 + (c[hot] - 0.5) * 0.2**0.5 for c in (x, y))
            yield pa.RecordBatch.from_arrays([pa.array(ids.astype(np.int64)), pa.array(x), pa.array(y), pa.array(z)], names=["obj_id", "x", "y", "z"])


class ScatterSynth(DataSource):
    @classmethod
    def name(cls) -> str:
        return "scatter_synth"

    def schema(self) -> str:
        return "obj_id long, x double, y double, z double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register_source(spark: SparkSession) -> None:
    spark.dataSource.register(ScatterSynth)
