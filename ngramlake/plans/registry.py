"""All registered queries of the search engine and their DuckDB counterparts."""

from __future__ import annotations

from ngramlake.plans import oracles, relational, workloads

QUERIES = workloads.QUERIES | relational.QUERIES
ORACLES = oracles.build() | relational.ORACLES
