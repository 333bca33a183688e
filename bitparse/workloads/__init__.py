"""Queries over the given tables, and the SQL that gives the same rows."""

from __future__ import annotations

from bitparse.workloads import applications, parsing, relational, structure

QUERIES = structure.QUERIES | parsing.QUERIES | applications.QUERIES | relational.QUERIES
ORACLE_SQL = structure.ORACLE_SQL | parsing.ORACLE_SQL | applications.ORACLE_SQL | relational.ORACLE_SQL
