"""Holds registered queries against their DuckDB SQL: python tests/oracle.py [DIR] [NAME...]."""

from __future__ import annotations

import math
import sys
import time
from pathlib import Path

import duckdb

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(d: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    return con


def plain(v: object) -> object:
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v + 0.0, 5)
    if hasattr(v, "as_tuple"):
        return round(float(v), 5) if v != int(v) else int(v)
    return v


def differences(spark, con: duckdb.DuckDBPyConnection, fn, sql: str, d: str) -> str | None:
    """None if both give the same rows, else what differs."""
    cur = con.execute(sql)
    names = [x[0] for x in cur.description]
    want = [dict(zip(names, r, strict=True)) for r in cur.fetchall()]
    df = fn(spark, d)
    if sorted(df.columns) != sorted(names):
        return f"columns {sorted(df.columns)} and {sorted(names)}"
    keys = sorted(names)
    a = sorted((tuple(plain(r[k]) for k in keys) for r in df.collect()), key=str)
    b = sorted((tuple(plain(r[k]) for k in keys) for r in want), key=str)
    if len(a) != len(b):
        return f"{len(a)} and {len(b)} rows"
    bad = [(x, y) for x, y in zip(a, b, strict=True) if x != y and not all(p == q or (isinstance(p, float) and isinstance(q, float) and abs(p - q) <= 2e-5) for p, q in zip(x, y, strict=True))]
    return f"{len(bad)} rows differ, as {bad[0]}" if bad else None


def main(d: str, wanted: list[str]) -> int:
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry
    from twoview.plans.registry import SQL, oracle_sql

    spark = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "6g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    con, sql, failed = duck(d), oracle_sql(d) | {k: v for k, v in entry.oracle_sql().items() if k not in SQL}, 0
    for name, fn in entry.queries().items():
        if (wanted and name not in wanted) or (not wanted and (name[:2] == "op" and name[2].isdigit() or name == "pipeline")):
            continue
        t = time.time()
        try:
            said = differences(spark, con, fn, sql[name], d) if name in sql else f"no SQL, {len(fn(spark, d).collect())} rows"
        except Exception as e:
            said = f"ERROR {str(e)[:600]}"
        if said and not said.startswith("no SQL"):
            failed += 1
        print(f"{name}: {said or 'same'} ({time.time() - t:.1f} s)", flush=True)
        spark.catalog.clearCache()
    return failed


if __name__ == "__main__":
    sys.exit(main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01", sys.argv[2:]))
