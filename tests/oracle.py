"""Run queries beside their DuckDB oracles: python tests/oracle.py DIR [NAME...]"""

from __future__ import annotations

import math
import os
import sys
import time

import duckdb
import pandas as pd

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for f in os.listdir(sf_dir):
        if f.endswith(".parquet"):
            path = f"{sf_dir}/{f}" + ("/*.parquet" if os.path.isdir(f"{sf_dir}/{f}") else "")
            con.sql(f"CREATE VIEW {f[:-8]} AS SELECT * FROM '{path}'")
    return con


def rows(df: pd.DataFrame) -> list[tuple]:
    df = df[sorted(df.columns)]

    def plain(v):
        if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and math.isnan(v)):
            return None
        if hasattr(v, "item"):
            v = v.item()
        if isinstance(v, pd.Timestamp):
            return v.isoformat()
        if isinstance(v, float) and v == int(v):
            return int(v)
        return v

    return sorted((tuple(plain(v) for v in r) for r in df.astype(object).itertuples(index=False)), key=repr)


def compare(spark, con, name: str, query, sql: str, sf_dir: str) -> str:
    """Empty if both agree."""
    got = query(spark, sf_dir).toPandas()
    want = con.sql(sql).df()
    if sorted(got.columns) != sorted(want.columns):
        return f"columns {sorted(got.columns)} and {sorted(want.columns)}"
    a, b = rows(got), rows(want)
    if a == b:
        return ""
    first = next(((x, y) for x, y in zip(a, b, strict=False) if x != y), None)
    only = len(set(a) - set(b)), len(set(b) - set(a))
    return f"{len(a)} and {len(b)} rows; {only} only in one; first {first}"


if __name__ == "__main__":
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    con, bad = connect(sys.argv[1]), 0
    oracles = entry.oracle_sql()
    for name, q in entry.queries().items():
        if sys.argv[2:] and not any(name.startswith(x) for x in sys.argv[2:]):
            continue
        began = time.time()
        try:
            said = compare(spark, con, name, q, oracles[name], sys.argv[1]) if name in oracles else f"no oracle, {q(spark, sys.argv[1]).count()} rows"
        except Exception as e:  # noqa: BLE001
            said = f"ERROR {str(e)[:700]}"
        ok = not said or said.startswith("no oracle")
        bad += not ok
        print(f"{'ok ' if ok else 'BAD'} {name} {time.time() - began:.1f}s {said}", flush=True)
    print("bad:", bad)
