"""Registered queries with their SQL, one module for each family."""

from __future__ import annotations

import importlib

from provspark.plans.registry import ORACLES, QUERIES

MODULES = ["lineage_queries", "leak_queries", "score_queries", "relational_queries", "stream_queries"]


def load() -> tuple[dict, dict]:
    for name in MODULES:
        importlib.import_module(f"provspark.plans.{name}")
    return QUERIES, ORACLES
