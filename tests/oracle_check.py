"""Runs queries beside their oracles: python tests/oracle_check.py SF_DIR [NAME...]."""

import os
import sys
import time
from collections import Counter
from datetime import date, datetime
from pathlib import Path

HOME = str(Path(__file__).resolve().parents[1])
sys.path.insert(0, HOME)
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    return con


def norm(v):
    if isinstance(v, float):
        return "nan" if v != v else repr(round(v, 6) + 0.0)
    if isinstance(v, bool) or v is None:
        return repr(v)
    if isinstance(v, (date, datetime)):
        return v.isoformat()
    return repr(v)


def compare(spark, con, name, query, sql, sf):
    df = query(spark, sf)
    cols = sorted(df.columns)
    got = Counter(tuple(norm(r[c]) for c in cols) for r in df.collect())
    rel = con.execute(sql)
    names = [d[0] for d in rel.description]
    if sorted(names) != cols:
        return f"columns {cols} against {sorted(names)}"
    at = [names.index(c) for c in cols]
    want = Counter(tuple(norm(r[i]) for i in at) for r in rel.fetchall())
    if got != want:
        return f"{sum(got.values())} rows against {sum(want.values())}; only here {list((got - want).items())[:3]}; only there {list((want - got).items())[:3]}"
    return None


if __name__ == "__main__":
    from pyspark.sql import SparkSession

    import __spark_entry__ as e

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    sf, only = sys.argv[1], sys.argv[2:]
    con, bad = connect(sf), []
    for name, sql in e.oracle_sql().items():
        if only and name not in only:
            continue
        t = time.time()
        try:
            why = compare(spark, con, name, e.queries()[name], sql, sf)
        except Exception as x:
            why = f"{type(x).__name__}: {str(x)[:400]}"
        print("ok " if why is None else "BAD", name, f"{time.time() - t:.1f}s", why or "", flush=True)
        if why:
            bad.append(name)
    print(len(bad), "differ:", *bad)
    os._exit(bool(bad))
