"""All registered queries: importing the modules registers theirs."""

from __future__ import annotations

from . import energy_queries, feed_queries, report_queries, store_queries  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
