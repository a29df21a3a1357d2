"""All registered queries of the methods, with their oracles."""

from __future__ import annotations

from lexbridge.plans import core, experiments, graph, paper_tables, relational, streams
from lexbridge.plans.core import flagship  # noqa: F401  the entry query
from lexbridge.plans.rounding import rounded_oracle, rounded_query

QUERIES = {}
ORACLES = {}
for _part in (core, graph, experiments, paper_tables, relational, streams):
    QUERIES.update({n: rounded_query(n, q) for n, q in _part.QUERIES.items()})
    ORACLES.update({n: rounded_oracle(n, q) for n, q in _part.ORACLES.items()})
