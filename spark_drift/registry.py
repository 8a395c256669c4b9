"""All queries of the engine by name, and their SQL twins where SQL can express them."""

from __future__ import annotations

from spark_drift.queries import displays, distances, mixtures, operators, projections, texts, workloads
from spark_drift.queries.base import ORACLES, QUERIES

MODULES = (distances, mixtures, displays, projections, operators, texts, workloads)

__all__ = ["MODULES", "ORACLES", "QUERIES"]
