"""Registration of queries with their SQL, and pieces of SQL that several share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


def registry() -> tuple[dict[str, Query], dict[str, str], Callable]:
    queries: dict[str, Query] = {}
    oracle: dict[str, str] = {}

    def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
        def add(fn: Query) -> Query:
            queries[name] = fn
            if sql is not None:
                oracle[name] = sql
            return fn

        return add

    return queries, oracle, query


#: lineitem with its surrogate key.
LINES = """li AS (SELECT *, l_orderkey * 10000 + row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_partkey, l_suppkey, l_linenumber) AS l_id FROM lineitem)"""
#: One row per bought line.
BOUGHT = """bought AS (SELECT o_custkey AS c_custkey, p_partkey, o_orderdate AS ts, p_retailprice, l_quantity
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey)"""


def stamps_sql(*rows: tuple[str, str]) -> str:
    return "s AS (SELECT * FROM (VALUES " + ", ".join(f"('{a}', TIMESTAMP '{b}')" for a, b in rows) + ") v(split, seed_time))"


YEAR = stamps_sql(("val", "1999-07-01"), ("test", "2000-07-01"), ("train", "1998-07-01"), ("train", "1997-07-01"), ("train", "1996-07-01"))
TWO_YEARS = stamps_sql(("val", "1997-07-01"), ("test", "1999-07-01"), ("train", "1995-07-02"))
DAYS = stamps_sql(("val", "2024-01-26"), ("test", "2024-01-28"), *(("train", f"2024-01-{d:02d}") for d in range(24, 1, -2)))
HALVES = stamps_sql(("val", "1999-07-01"), ("test", "2000-07-01"), *(("train", d) for d in ("1998-12-31", "1998-07-02", "1998-01-01", "1997-07-03", "1997-01-02", "1996-07-04", "1996-01-04")))
