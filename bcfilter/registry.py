"""All queries of the filter engine, gathered from the query modules."""

from __future__ import annotations

from .plans import core, relational, streams, workloads  # noqa: F401
from .plans.base import ORACLE_SQL, QUERIES  # noqa: F401
