"""Distances over event streams."""
