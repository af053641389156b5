"""The named queries of the library and, where SQL can express them, the SQL that gives the same rows."""

from __future__ import annotations

from placelink.oracles import ORACLES
from placelink.plans.experiments import QUERIES as _EXPERIMENTS
from placelink.streaming.queries import QUERIES as _STREAMS

QUERIES = _EXPERIMENTS | _STREAMS

__all__ = ["ORACLES", "QUERIES"]
