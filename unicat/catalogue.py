"""Imports every module that registers queries."""

from .registry import QUERIES, SQL
from .workloads import baseline_queries, chain_queries, experiment_queries, raster_queries, relational_queries, surface_queries, text_queries  # noqa: F401

__all__ = ["QUERIES", "SQL"]
