"""Compare a registered query with its SQL run by DuckDB on the same files."""

import math
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        if os.path.exists(path):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def cell(x):
    if isinstance(x, bool) or x is None:
        return str(x)
    if isinstance(x, float):
        return "nan" if math.isnan(x) else f"{x:.6g}" if x else "0"
    return str(x)


def rows(names, data):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple(cell(r[i]) for i in order) for r in data), sorted(names)


def differ(spark, con, sf_dir, query, sql):
    """None if equal, else what differs."""
    df = query(spark, sf_dir)
    mine, cols = rows(df.columns, [tuple(r) for r in df.collect()])
    rel = con.sql(sql)
    other, cols2 = rows(rel.columns, rel.fetchall())
    if cols != cols2:
        return f"columns {cols} and {cols2}"
    if len(mine) != len(other):
        return f"{len(mine)} and {len(other)} rows"
    bad = [(a, b) for a, b in zip(mine, other) if a != b]
    kinds = {k: v for k, v in df.dtypes}
    return None if not bad else f"{len(bad)} of {len(mine)} rows, first {bad[0]}; {kinds}"


if __name__ == "__main__":
    import sys
    import time

    sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config(
        "spark.driver.memory", "6g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    import importlib

    mod = importlib.import_module(sys.argv[2])
    con = connect(sys.argv[1])
    sql = mod.SQL
    for name, q in mod.QUERIES.items():
        if len(sys.argv) > 3 and name not in sys.argv[3:]:
            continue
        t = time.time()
        try:
            if name in sql:
                why = differ(spark, con, sys.argv[1], q, sql[name])
            else:
                why = f"no SQL; {len(q(spark, sys.argv[1]).collect())} rows"
        except Exception as e:
            why = "ERROR " + str(e)[:700]
        print(f"{name} {time.time() - t:.1f}s", "ok" if why is None else why, flush=True)
