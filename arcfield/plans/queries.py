"""All queries of the engine, by key, and their SQL."""

from __future__ import annotations

from arcfield.plans import cost, index_queries, region_queries, relational_queries, stream_queries, zone_queries

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
for _module in (cost, zone_queries, region_queries, index_queries, relational_queries, stream_queries):
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES
