"""All queries of the engine by name, with their SQL where there is any."""

from __future__ import annotations

from . import closed_set, probe, relational_queries, streaming_queries, text

_MODULES = (probe, text, relational_queries, streaming_queries, closed_set)

QUERIES = {name: fn for m in _MODULES for name, fn in m.QUERIES.items()}
ORACLE_SQL = {name: sql for m in _MODULES for name, sql in m.ORACLE_SQL.items()}
