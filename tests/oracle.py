"""Run queries beside their SQL: python tests/oracle.py SF_DIR [NAME...]. Columns are compared by name, rows without order."""

import math
import os
import sys
import time

import duckdb

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def connect(sf_dir):
    con = duckdb.connect()
    for f in sorted(os.listdir(sf_dir)):
        con.execute(f"create view {f.removesuffix('.parquet')} as select * from '{sf_dir}/{f}'")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 6) + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    if isinstance(v, bool):
        return v
    return v


def difference(df, con, sql):
    """None if equal, else what differs."""
    cur = con.execute(sql)
    names = [c[0] for c in cur.description]
    if sorted(names) != sorted(df.columns):
        return f"columns {sorted(df.columns)} and {sorted(names)}"
    order = sorted(names)
    want = sorted((tuple(plain(dict(zip(names, r))[c]) for c in order) for r in cur.fetchall()), key=str)
    got = sorted((tuple(plain(r[c]) for c in order) for r in df.collect()), key=str)
    if len(want) != len(got):
        return f"{len(got)} rows and {len(want)}"
    for a, b in zip(got, want):
        if a != b:
            return f"{a} and {b}"
    return None


def main():
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    sf_dir, names = sys.argv[1], sys.argv[2:]
    con, qs, sql = connect(sf_dir), entry.queries(), entry.oracle_sql()
    bad = 0
    for n in names or [k for k in qs if k[:2] != "op" and k != "pipeline"]:
        t = time.time()
        try:
            df = qs[n](spark, sf_dir)
            said = difference(df, con, sql[n]) if n in sql else f"rows {df.count()}"
        except Exception as e:
            said = f"{type(e).__name__} {str(e)[:300]}"
        ok = said is None or said.startswith("rows ")
        bad += not ok
        print("ok  " if ok else "BAD ", n, f"{time.time() - t:.1f}s", said or "", flush=True)
    return bad


if __name__ == "__main__":
    sys.exit(main())
