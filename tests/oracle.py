"""Runs queries against their SQL in DuckDB: the same comparison for tests and by hand (python tests/oracle.py SF NAME...)."""

import math
import sys
import time

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    import duckdb

    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet')")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6)
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    if hasattr(v, "tzinfo") and v.tzinfo is not None:
        return v.replace(tzinfo=None)
    return v


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    return [columns[k] for k in order], sorted((tuple(plain(r[k]) for k in order) for r in rows), key=repr)


def compare(spark, con, name, sf_dir, query, sql):
    df = query(spark, sf_dir)
    got = rows_of(df.columns, [tuple(r) for r in df.collect()])
    cur = con.execute(sql)
    want = rows_of([d[0] for d in cur.description], cur.fetchall())
    if got[0] != want[0]:
        return f"columns {got[0]} and {want[0]}"
    if len(got[1]) != len(want[1]):
        return f"{len(got[1])} and {len(want[1])} rows: {next(((a, b) for a, b in zip(got[1], want[1], strict=False) if a != b), '')}"
    bad = [(a, b) for a, b in zip(got[1], want[1], strict=True) if a != b]
    return f"{len(bad)} rows differ, first {bad[0]}" if bad else ""


if __name__ == "__main__":
    import os

    sys.path.insert(0, os.getcwd())
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    sf_dir = f"/root/testdata/{sys.argv[1]}"
    con, queries, sql = connect(sf_dir), entry.queries(), entry.oracle_sql()
    for name in sys.argv[2:] or [n for n in queries if not n.startswith(("op", "pipeline")) or n.startswith("optimal")]:
        began = time.time()
        try:
            if name in sql:
                said = compare(spark, con, name, sf_dir, queries[name], sql[name]) or "same"
            else:
                said = f"no SQL, {queries[name](spark, sf_dir).count()} rows"
        except Exception as e:
            said = "ERROR " + " ".join(str(e).split())[:600]
        print(f"{name}: {said} ({time.time() - began:.1f} s)", flush=True)
