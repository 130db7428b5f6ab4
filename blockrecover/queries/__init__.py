"""All queries of the recovery engine with their DuckDB twins."""

from __future__ import annotations

from . import analytics, blocks, carving, extended, recovery, streams

QUERIES = blocks.QUERIES | carving.QUERIES | recovery.QUERIES | analytics.QUERIES | streams.QUERIES | extended.QUERIES
ORACLE_SQL = blocks.ORACLE_SQL | carving.ORACLE_SQL | recovery.ORACLE_SQL | analytics.ORACLE_SQL | streams.ORACLE_SQL | extended.ORACLE_SQL
