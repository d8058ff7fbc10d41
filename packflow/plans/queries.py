"""All registered queries of the engine, by import."""

from __future__ import annotations

from packflow.plans import model_queries, packing_queries, recovery_queries, relational_queries, surface_queries, workload_queries  # noqa: F401
from packflow.plans.registry import ORACLES, QUERIES
from packflow.streaming import queries as streaming_queries  # noqa: F401

__all__ = ["ORACLES", "QUERIES"]
