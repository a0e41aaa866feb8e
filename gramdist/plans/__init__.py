"""Choices made before a plan runs: block side, route, bounds."""
