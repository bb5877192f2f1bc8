"""Named queries over the given tables and their SQL equivalents."""

from neardup.plans import baselines, core, measures, surrounding, workloads  # noqa: F401
from neardup.plans.registry import QUERIES, SQL

__all__ = ["QUERIES", "SQL"]
