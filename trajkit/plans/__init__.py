"""Registered queries, workloads and their SQL."""

from trajkit.plans import cluster_queries, relops, rule_queries, stream_queries, workloads  # noqa: F401
from trajkit.plans.base_queries import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
