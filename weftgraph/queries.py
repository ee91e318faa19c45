"""All registered queries of the graph engine and their SQL."""

from __future__ import annotations

from weftgraph import queries_create, queries_match, queries_partition, queries_paths, queries_solve, queries_stream
from weftgraph.catalog import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES", "queries_create", "queries_match", "queries_partition", "queries_paths", "queries_solve", "queries_stream"]
