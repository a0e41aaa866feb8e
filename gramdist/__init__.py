"""Exact weighted edit distances between compressed strings, on Spark."""
