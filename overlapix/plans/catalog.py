"""All registered queries of the engine."""

from __future__ import annotations

from overlapix.plans import catalog_hash, catalog_relational, catalog_sets  # noqa: F401
from overlapix.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
