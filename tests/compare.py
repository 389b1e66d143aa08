"""Runs queries and their DuckDB oracles side by side: python tests/compare.py [FOLDER] [KEY...]"""

import glob
import os
import sys
import time

import duckdb

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def connect(folder):
    c = duckdb.connect()
    for p in glob.glob(f"{folder}/*.parquet"):
        c.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return c


def plain(v):
    return round(float(v), 6) if isinstance(v, (float, int)) and not isinstance(v, bool) or type(v).__name__ == "Decimal" else str(v)


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return [tuple(plain(r[i]) for i in order) for r in rows]


def difference(spark, con, query, oracle, folder):
    """None if both give the same rows under the same names."""
    df = query(spark, folder)
    got = [tuple(r) for r in df.collect()]
    cur = con.execute(oracle)
    names = [d[0] for d in cur.description]
    want = cur.fetchall()
    if sorted(df.columns) != sorted(names):
        return f"columns {df.columns} and {names}"
    key = lambda r: tuple(map(str, r))
    a, b = sorted(rows_of(df.columns, got), key=key), sorted(rows_of(names, want), key=key)
    if a != b:
        odd = next(((x, y) for x, y in zip(a, b) if x != y), None)
        return f"{len(a)} and {len(b)} rows; first difference {odd}"
    return None


if __name__ == "__main__":
    sys.path.insert(0, ROOT)
    os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    folder = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    con, q, o = connect(folder), entry.queries(), entry.oracle_sql()
    for name in sys.argv[2:] or [k for k in q if not k.startswith("op") and k != "pipeline"]:
        began = time.time()
        try:
            said = difference(spark, con, q[name], o[name], folder) if name in o else f"rows {q[name](spark, folder).count()}"
        except Exception as e:  # noqa: BLE001
            said = f"{type(e).__name__} {str(e)[:400]}"
        print(f"{'ok' if said is None else said if said.startswith('rows ') else 'DIFF ' + said}\t{name}\t{time.time() - began:.1f}", flush=True)
