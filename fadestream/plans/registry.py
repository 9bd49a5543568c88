"""Named queries with the SQL that checks them."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, fn: Query, sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is registered already")
    QUERIES[name] = fn
    if sql is not None:
        SQL[name] = sql


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def keep(fn: Query) -> Query:
        add(name or fn.__name__, fn, sql)
        return fn

    return keep


def rounded(v: float, digits: int) -> float:
    """Halves away from zero, as SQL engines round."""
    scaled = abs(v) * 10**digits
    return math.copysign(math.floor(scaled + 0.5) / 10**digits, v) if math.isfinite(scaled) else v
