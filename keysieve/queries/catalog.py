"""All queries of the library by name, and their SQL."""

from __future__ import annotations

from . import experiments, relational_queries, sketches, star_queries, stream_queries

QUERIES, ORACLES = {}, {}
for part in (sketches, star_queries, experiments, relational_queries, stream_queries):
    if QUERIES.keys() & part.reg.queries.keys():
        raise ValueError("two queries have one name")
    QUERIES |= part.reg.queries
    ORACLES |= part.reg.sql
