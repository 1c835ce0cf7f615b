"""All queries of the join engine by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from adaptivejoin.plans import applications, core, kernels, relational, strategies
from adaptivejoin.streaming import queries as streaming

MODULES = (core, kernels, strategies, applications, relational, streaming)
QUERIES = {k: v for m in MODULES for k, v in m.QUERIES.items()}
ORACLES = {k: v for m in MODULES for k, v in m.ORACLES.items()}
