"""Registered queries by area, each module with ``QUERIES`` (name to function) and ``SQL`` (name to DuckDB text)."""
