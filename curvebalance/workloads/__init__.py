"""Queries over the given tables, one for each method, variant, baseline, measure and operator, and the SQL that must give the same rows."""

from __future__ import annotations

from . import curvesets, graphs, relational, search, trees

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
for _m in (curvesets, trees, search, graphs, relational):
    QUERIES |= _m.QUERIES
    ORACLE_SQL |= _m.ORACLE
