"""Registry of the queries on the method's own operators, with their SQL twins."""

from __future__ import annotations

from catalogflow.plans import answers, classify, dedup, extraction, metadata, portal, probe, surface, variants  # noqa: F401
from catalogflow.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
