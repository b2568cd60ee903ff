"""The registry of queries: a name, a function of (spark, sf_dir), and the SQL that checks it."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def zeros(checks: list[str], checked: str) -> str:
    """The oracle of invariant queries: no violations among as many rows as `checked` counts."""
    return " union all ".join(f"select '{c}' as check_name, cast(0 as bigint) as violations, cast(({checked}) as bigint) as checked" for c in checks)
