"""Queries by section of the survey."""

from halograph.queries import around, graphs, models  # noqa: F401
