"""Registered queries, each with the SQL that DuckDB runs over the same tables where SQL can express it."""
