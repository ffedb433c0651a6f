"""Runs registered queries against DuckDB: python tests/oracle.py SF_DIR [NAME...]."""

import math
import os
import sys
import time
from datetime import date, datetime
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet')").fetchall()
    return con


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "null"
    if isinstance(v, bool):
        return str(v)
    if isinstance(v, datetime | date):
        return v.isoformat()
    if isinstance(v, int | float):
        return repr(round(float(v), 9))
    return str(v)


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return [columns[i] for i in order], sorted(tuple(plain(r[i]) for i in order) for r in rows)


def compare(df, con, sql):
    """None, or what differs."""
    got = rows_of(df.columns, [tuple(r) for r in df.collect()])
    cur = con.execute(sql)
    want = rows_of([c[0] for c in cur.description], cur.fetchall())
    if got[0] != want[0]:
        return f"columns {got[0]} {want[0]}"
    if got[1] != want[1]:
        odd = sorted(set(got[1]) ^ set(want[1]))[:4]
        return f"{len(got[1])} and {len(want[1])} rows, for instance {odd}"
    return None


if __name__ == "__main__":
    os.environ["PYTHONPATH"] = str(Path(__file__).resolve().parent.parent)
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    con, sql, queries = connect(sys.argv[1]), entry.oracle_sql(), entry.queries()
    names = sys.argv[2:] or [n for n in queries if not n.startswith("op") and n != "pipeline"]
    bad = 0
    for n in names:
        t0 = time.time()
        try:
            df = queries[n](spark, sys.argv[1])
            why = compare(df, con, sql[n]) if n in sql else f"(no SQL) {df.count()} rows"
        except Exception as e:
            why = f"{type(e).__name__}: {str(e)[:300]}"
        print(n, "ok" if why is None else why, round(time.time() - t0, 1), flush=True)
        bad += why is not None and not why.startswith("(no SQL)")
    print("differ:", bad)
