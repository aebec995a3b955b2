"""Registered queries of the engine: each a call of its operators, with DuckDB SQL that
computes the same result independently."""

from __future__ import annotations

from collections.abc import Callable

from . import core, fits, measured, relational, runtime


def queries() -> dict[str, Callable]:
    return {n: f for part in (core, relational, runtime, measured, fits) for n, (f, _) in part.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {n: q for part in (core, relational, runtime, measured, fits) for n, (_, q) in part.QUERIES.items() if q}
