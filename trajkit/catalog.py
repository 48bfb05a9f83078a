"""All queries of the library and their oracles, gathered from the query modules."""

from __future__ import annotations

import importlib

from trajkit.registered import ORACLES, QUERIES, query

__all__ = ["ORACLES", "QUERIES", "query"]

for _part in ("objective", "capture", "policies", "scheduling", "storage", "serving", "measuring", "surface"):
    importlib.import_module(f"trajkit.queries.{_part}")
