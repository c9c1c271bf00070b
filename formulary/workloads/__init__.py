"""Every registered workload of the corpus engine."""

from ..registry import ORACLES, QUERIES
from . import analysis, dedup, extraction, inspection, latex, prefilter, relational, scoring  # noqa: F401

__all__ = ["ORACLES", "QUERIES"]
