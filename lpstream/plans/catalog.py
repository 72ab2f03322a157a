"""The query catalogue: one function and, where SQL can state it, one DuckDB text a key."""

from __future__ import annotations

from ..operators import functions_queries, relational
from ..streaming import streams
from . import methods, numeric

PARTS = [methods, numeric, relational, functions_queries, streams]


def queries() -> dict:
    out: dict = {}
    for part in PARTS:
        out |= part.queries()
    return out


def oracle_sql() -> dict[str, str]:
    out: dict = {}
    for part in PARTS:
        out |= part.oracle_sql()
    return out
