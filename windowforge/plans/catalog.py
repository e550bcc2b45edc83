"""All queries of the library by name, and their SQL."""

from __future__ import annotations

from windowforge.plans import queries_evals, queries_method, queries_tables, queries_windows

QUERIES = {**queries_method.QUERIES, **queries_evals.QUERIES, **queries_tables.QUERIES, **queries_windows.QUERIES}
ORACLE_SQL = {**queries_method.ORACLE_SQL, **queries_evals.ORACLE_SQL, **queries_tables.ORACLE_SQL, **queries_windows.ORACLE_SQL}
