"""Queries over the given tables: one for each method, variant, baseline, measure and workload."""

from gradsift.catalog import baselines, measures, selection, steps, surface, workloads  # noqa: F401
from gradsift.catalog.registry import QUERIES, SQL

__all__ = ["QUERIES", "SQL"]
