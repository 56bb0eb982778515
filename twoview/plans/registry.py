"""All queries of the core library and their SQL; the modules below fill them in."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
#: SQL text, or a function of the tables' folder that makes it, where learned constants go into it.
SQL: dict[str, str | Callable[[str], str]] = {}
#: The tables that SQL with learned constants is made for.
ORACLE_DIR = "/root/testdata/sf0.01"


def query(name: str, sql: str | Callable[[str], str] | None = None) -> Callable[[Query], Query]:
    """Registers a query and, where SQL can express it, its DuckDB form."""

    def add(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql is not None:
            SQL[name] = sql
        return fn

    return add


def oracle_sql(d: str = ORACLE_DIR) -> dict[str, str]:
    """DuckDB SQL by query; that with learned constants is for the tables of d, and left out where there are none."""
    from pathlib import Path

    there = Path(d, "embeddings.parquet").exists()
    return {name: sql(d) if callable(sql) else sql for name, sql in SQL.items() if there or not callable(sql)}


from twoview.plans import relational_queries, stream_queries, vector_queries  # noqa: E402, F401, I001
from twoview.plans import learned_queries  # noqa: E402, F401
