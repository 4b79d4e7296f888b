"""Tuple attribution for relational queries on Spark."""
