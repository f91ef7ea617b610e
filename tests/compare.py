"""Runs registered queries beside their SQL twins: python tests/compare.py [directory] [names...]"""

from __future__ import annotations

import math
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def session():
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def value(x):
    if isinstance(x, float):
        return "nan" if math.isnan(x) else f"{x + 0.0:.6f}"
    if hasattr(x, "isoformat"):
        return x.isoformat()[:26]
    if type(x).__name__ == "Decimal":
        return f"{float(x):.6f}"
    return str(x)


def compare(spark, name: str, run, sql: str | None, directory: str) -> str:
    import duckdb

    began = time.time()
    got = run(spark, directory)
    rows = [r.asDict() for r in got.collect()]
    took = time.time() - began
    if sql is None:
        return f"rows-only {len(rows)} {took:.1f}s"
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{directory}/{t}.parquet')")
    began = time.time()
    cursor = con.execute(sql)
    names = [d[0] for d in cursor.description]
    want = [dict(zip(names, r, strict=True)) for r in cursor.fetchall()]
    sql_took = time.time() - began
    if sorted(names) != sorted(got.columns):
        return f"COLUMNS {sorted(got.columns)} {sorted(names)}"
    key = lambda r: tuple(value(r[c]) for c in sorted(names))
    a, b = sorted(map(key, rows)), sorted(map(key, want))
    if a != b:
        only_a, only_b = sorted(set(a) - set(b))[:3], sorted(set(b) - set(a))[:3]
        return f"DIFFERENT {len(a)} {len(b)} {only_a} {only_b}"
    return f"equal {len(a)} {took:.1f}s sql {sql_took:.1f}s"


if __name__ == "__main__":
    import __spark_entry__ as entry

    directory = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"
    spark = session()
    for name, run in entry.queries().items():
        if len(sys.argv) > 2 and name not in sys.argv[2:]:
            continue
        try:
            said = compare(spark, name, run, entry.oracle_sql().get(name), directory)
        except Exception as e:
            said = f"ERROR {type(e).__name__} {str(e)[:400]}"
        print(name, said, flush=True)
