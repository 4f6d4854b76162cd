"""All queries of the engine, with their DuckDB counterparts."""

from __future__ import annotations

from . import relational_queries, sampling_queries, streaming_queries

_PARTS = (sampling_queries, relational_queries, streaming_queries)
QUERIES = {k: v for m in _PARTS for k, v in m.QUERIES.items()}
ORACLES = {k: v for m in _PARTS for k, v in m.ORACLES.items()}
