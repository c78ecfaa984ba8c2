"""All named queries of the engine; importing this module registers them."""

from __future__ import annotations

from reuse_engine.plans import methods, stream_queries, surround, workloads  # noqa: F401
from reuse_engine.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
