"""Registered queries by family; each module has QUERIES and ORACLES."""

from __future__ import annotations

import importlib

FAMILIES: list[str] = ["media", "buckets", "scenes", "quality", "dedup", "flow", "planner", "kernels", "inpainting", "surface", "streams"]


def load() -> tuple[dict, dict]:
    """All queries and all oracles of the families."""
    queries: dict = {}
    oracles: dict = {}
    for name in FAMILIES:
        module = importlib.import_module(f"{__name__}.{name}")
        queries |= module.QUERIES
        oracles |= module.ORACLES
    return queries, oracles
