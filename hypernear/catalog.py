"""Named queries over the given tables, with the SQL that must agree."""

from .plans import experiments, groups, searches, workloads  # noqa: F401
from .plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
