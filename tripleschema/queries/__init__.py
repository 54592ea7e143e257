"""Registered queries, each with an independent DuckDB statement of the same result where SQL can state it."""
