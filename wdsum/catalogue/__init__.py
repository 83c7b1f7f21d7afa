"""All queries of the engine and their SQL in DuckDB's dialect."""

from __future__ import annotations

from . import core, measures, relational, streams
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "core", "measures", "relational", "streams"]
