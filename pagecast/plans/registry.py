"""Names, queries and their SQL counterparts, collected as modules define them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def tie_break(digits: int) -> float:
    """A thousandth of the last digit kept: breaks ties alike in every engine."""
    return 1.23 * 10.0 ** -(digits + 3)


def shifted(sql: str) -> str:
    """Every ``round(x, k)`` of a statement as ``round((x) + tie_break(k), k)``."""
    at = sql.find("round(")
    if at < 0:
        return sql
    depth, comma, i = 1, -1, at + 6
    while depth:
        c = sql[i]
        depth += (c == "(") - (c == ")")
        if c == "," and depth == 1:
            comma = i
        i += 1
    inner, digits = shifted(sql[at + 6 : comma]), int(sql[comma + 1 : i - 1])
    return f"{sql[:at]}round(({inner}) + {tie_break(digits):.10f}, {digits}){shifted(sql[i:])}"


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def register(fn: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = shifted(sql)
        return fn

    return register
