"""Exact distance queries on large graphs as Spark dataflows."""
