"""Runs queries() against oracle_sql() as the driver does: rows, columns and values, order aside."""

import math
import os
import sys

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(x):
    if x is None:
        return None
    if isinstance(x, float):
        return None if math.isnan(x) else round(x, 6)
    if isinstance(x, (list, tuple)):
        return tuple(plain(y) for y in x)
    if hasattr(x, "asDict"):
        return tuple(plain(y) for y in x)
    return x


def compare(spark, name, query, sql, sf_dir, con):
    frame = query(spark, sf_dir)
    columns = sorted(frame.columns)
    got = sorted((tuple(plain(r[c]) for c in columns) for r in frame.collect()), key=repr)
    answer = con.execute(sql)
    there = [c[0] for c in answer.description]
    if sorted(there) != columns:
        return f"columns {columns} / {sorted(there)}"
    at = [there.index(c) for c in columns]
    want = sorted((tuple(plain(r[i]) for i in at) for r in answer.fetchall()), key=repr)
    if len(got) != len(want):
        return f"rows {len(got)} / {len(want)}"
    bad = [(a, b) for a, b in zip(got, want) if a != b]
    return f"values {bad[:3]} ({len(bad)} of {len(got)})" if bad else ""


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return con


if __name__ == "__main__":
    import time

    sys.path.insert(0, "/root/repo")
    from pyspark.sql import SparkSession

    import __spark_entry__ as E

    sf_dir, names = sys.argv[1], sys.argv[2:]
    spark = SparkSession.builder.master(f"local[{os.environ.get('ORACLE_CPUS', 8)}]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    con, q, o = connect(sf_dir), E.queries(), E.oracle_sql()
    for name in q:
        if names and not any(name.startswith(n) for n in names):
            continue
        t = time.time()
        try:
            out = compare(spark, name, q[name], o[name], sf_dir, con) if name in o else f"no sql, {q[name](spark, sf_dir).count()} rows"
        except Exception as e:
            out = f"{type(e).__name__} {str(e)[:300]}"
        print(f"{name:40s} {time.time() - t:6.1f} {out or 'ok'}".replace("\n", " "), flush=True)
