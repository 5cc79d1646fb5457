"""Registered queries of the library itself, each with a DuckDB oracle where SQL can express it."""

from __future__ import annotations

from . import experiments, features, functions, quantizers, search, streams, surroundings, vectors
from .common import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "experiments", "features", "functions", "quantizers", "search", "streams", "surroundings", "vectors"]
