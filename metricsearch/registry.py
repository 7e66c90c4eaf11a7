"""All queries of the library and their DuckDB twins."""

from __future__ import annotations

from .operators import relational
from .plans import workloads
from .streaming import events

QUERIES = {**relational.QUERIES, **workloads.QUERIES, **events.QUERIES}
ORACLES = {**relational.ORACLES, **workloads.ORACLES, **events.ORACLES}
