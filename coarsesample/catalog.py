"""All queries of the engine, with DuckDB SQL where SQL can express them."""

from __future__ import annotations

from coarsesample.plans import registry_ops, registry_pick, registry_stats, registry_work
from coarsesample.plans.registry import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES", "registry_ops", "registry_pick", "registry_stats", "registry_work"]
