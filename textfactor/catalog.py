"""All registered queries of the engine's own operators."""

from __future__ import annotations

from textfactor import measure_queries, queries, surface_queries, workload_queries  # noqa: F401
from textfactor.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
