"""Registered queries, workloads and their DuckDB oracles."""
