"""All queries that are not of the corpus operators."""

from __future__ import annotations

from ..streaming import queries as streaming_queries
from . import geometry_queries, layout_queries, relational_queries, stats_queries, workload_queries

MODULES = (geometry_queries, layout_queries, stats_queries, relational_queries, streaming_queries, workload_queries)
QUERIES = {name: f for m in MODULES for name, f in m.QUERIES.items()}
ORACLES = {name: sql for m in MODULES for name, sql in m.SQL.items()}
ORACLES["stream_kd_assign"] = ORACLES["kd_leaf_counts"]
