"""Registered queries against their SQL on the smallest tables."""

import os

import duckdb
import pandas as pd
import pytest
from conftest import SMALL

from multiscale_scatter.queries import registry
from multiscale_scatter.sources.fixtures import TABLES

NAMES = list(registry.ORACLES)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        p = f"{SMALL}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return con


def plain(df: pd.DataFrame) -> list[tuple]:
    df = df[sorted(df.columns)]
    cell = lambda v: None if v is None or v is pd.NA or v != v else round(float(v), 4) if isinstance(v, (int, float)) or hasattr(v, "dtype") else str(v)
    return sorted((tuple(cell(v) for v in r) for r in df.astype(object).itertuples(index=False)), key=str)


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, duck, name):
    ours = registry.QUERIES[name](spark, SMALL).toPandas()
    theirs = duck.sql(registry.ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert plain(ours) == plain(theirs)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["cte_levels", "density_theta", "effective_theta", "provisioning", "tile_lattice", "udtf_lattice", "viewport_capacity"])
def test_reads_a_given_table(spark, name):
    assert any(SMALL in f for f in registry.QUERIES[name](spark, SMALL).inputFiles())
