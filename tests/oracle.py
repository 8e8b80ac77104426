"""Side-by-side check of queries() against oracle_sql() in DuckDB: rows, columns and values in any order."""

from __future__ import annotations

import os
import sys

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        if os.path.exists(path):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path if os.path.isfile(path) else path + '/*.parquet'}'")
    return con


def _plain(v):
    if isinstance(v, float):
        return repr(round(v, 9))
    return str(v)


def differences(spark_df, sql: str, con) -> str:
    """Empty if equal; else what differs."""
    got = spark_df.toPandas()
    want = con.execute(sql).df()
    if sorted(got.columns) != sorted(want.columns):
        return f"columns {sorted(got.columns)} and {sorted(want.columns)}"
    columns = sorted(got.columns)
    a, b = [tuple(map(str, r)) for r in rows_of(got, columns)], [tuple(map(str, r)) for r in rows_of(want, columns)]
    if sorted(a) != sorted(b):
        only = [r for r in a if r not in set(b)][:3], [r for r in b if r not in set(a)][:3]
        return f"{len(a)} and {len(b)} rows; {columns}; only here {only[0]}; only there {only[1]}"
    return ""


def rows_of(d, columns):
    for r in d[columns].astype(object).itertuples(index=False):
        yield tuple("null" if v is None or (isinstance(v, float) and v != v) or str(v) in ("<NA>", "NaT") else _plain(float(v)) if isinstance(v, float) else _plain(v.item() if hasattr(v, "item") else v) for v in r)


if __name__ == "__main__":
    import time

    sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    import __spark_entry__ as e
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    sf = os.environ.get("SF_DIR", "/root/testdata/sf0.01")
    con, queries, sql = connect(sf), e.queries(), e.oracle_sql()
    names = [n for n in queries if not sys.argv[1:] or any(n.startswith(a) for a in sys.argv[1:])]
    for n in names:
        began = time.time()
        try:
            df = queries[n](spark, sf)
            said = differences(df, sql[n], con) if n in sql else f"no sql, {df.count()} rows"
        except Exception as x:
            said = f"{type(x).__name__}: {str(x)[:600]}"
        print(f"{n}: {said or 'equal'} ({time.time() - began:.1f} s)", flush=True)
