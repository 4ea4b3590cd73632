"""Driver catalogue: every method as a query over the given tables, with its SQL beside it."""

from . import graphs, planning, scans, streams, surround  # noqa: F401 - they fill the registry
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
