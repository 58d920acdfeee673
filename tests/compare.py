"""Compare registered queries with their DuckDB twins on one scale; run as a script or from tests."""

from __future__ import annotations

import math
import os
import sys
import time

import duckdb

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def connect(sf_dir: str):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def _plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return None
    if isinstance(v, (int, bool)):
        return float(v)
    return round(float(v), 4) if not isinstance(v, str) and hasattr(v, "__float__") else str(v)


def rows(columns, data) -> list:
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    return sorted((tuple(_plain(r[k]) for k in order) for r in data), key=repr)


def mismatch(spark, con, sf_dir: str, query, sql: str) -> str:
    df = query(spark, sf_dir)
    got = rows(df.columns, df.collect())
    cur = con.execute(sql)
    names = [c[0] for c in cur.description]
    want = rows(names, cur.fetchall())
    if sorted(df.columns) != sorted(names):
        return f"columns {df.columns} and {names}"
    if got != want:
        odd = [(a, b) for a, b in zip(got, want) if a != b][:2]
        return f"{len(got)} and {len(want)} rows, {odd}"
    return ""


if __name__ == "__main__":
    sys.path.insert(0, ".")
    import __spark_entry__ as entry
    from benchvary.session import local_session

    spark, con, sf_dir = local_session(os.environ.get("TEST_CPUS", "8")), connect(sys.argv[1]), sys.argv[1]
    q, sql = entry.queries(), entry.oracle_sql()
    for name in sys.argv[2:] or sql:
        began = time.time()
        try:
            said = mismatch(spark, con, sf_dir, q[name], sql[name]) or "ok"
        except Exception as e:  # noqa: BLE001
            said = f"error {str(e)[:600]}"
        print(name, said, round(time.time() - began, 1), flush=True)
