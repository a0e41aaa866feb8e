"""Kernels (numpy, no Spark) and the functions registered for SQL."""
