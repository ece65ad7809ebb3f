"""Registered queries: the methods on the given tables, each with its DuckDB oracle where SQL can say it."""
