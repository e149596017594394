"""Registered queries with the SQL that another engine checks them by."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def w(x: str) -> str:
    """Words of a text, as functions.words."""
    return f"list_filter(regexp_split_to_array(lower({x}), '[ \\n]+'), lambda t: t <> '')"


def h(seed: str, *cols: str) -> str:
    """functions.hash_unit."""
    return f"('0x' || substr(md5(concat_ws('-', '{seed}', {', '.join(cols)})), 1, 8))::BIGINT"


def grams(x: str, n: int) -> str:
    return f"(CASE WHEN len({x}) >= {n} THEN list_distinct(list_transform(range(1, len({x}) - {n - 2}), lambda i: array_to_string({x}[i:i + {n - 1}], ' '))) ELSE [] END)"


def five(a: str, b: str) -> str:
    return f"(1 + least(4, (5 * {a}) // greatest(1, {b})))::INT"


def load() -> tuple[dict[str, Query], dict[str, str]]:
    from . import methods, operators, streams, workloads  # noqa: F401

    return QUERIES, SQL
