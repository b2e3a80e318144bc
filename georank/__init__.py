"""Continuous top-m rank aggregation over spatial query streams, on Spark."""
