"""python -m tests.compare [sf0.01 [name...]]: every query with SQL against DuckDB."""

import glob
import os
import sys
import time

SMALLEST = "/root/testdata/sf0.001"


def connection(sf_dir):
    import duckdb

    con = duckdb.connect()
    for path in glob.glob(f"{sf_dir}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def sorted_rows(table):
    return sorted(map(repr, (tuple(r.values()) for r in table.select(sorted(table.column_names)).to_pylist())))


def rows_of(con, sql):
    table = con.sql(sql).arrow()
    table = table.read_all() if hasattr(table, "read_all") else table
    return sorted(table.column_names), sorted_rows(table)


def main(sf_dir, names):
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    con, sql, wrong = connection(sf_dir), entry.oracle_sql(), 0
    for name, query in entry.queries().items():
        if names and name not in names:
            continue
        began = time.time()
        got = query(spark, sf_dir).toArrow()
        took = time.time() - began
        told = "no SQL"
        if name in sql:
            columns, want = rows_of(con, sql[name])
            same = sorted(got.column_names) == columns and sorted_rows(got) == want
            told, wrong = "equal" if same else "DIFFERS", wrong + (not same)
        print(f"{name} {took:.1f} s, {got.num_rows} rows: {told}", flush=True)
    return wrong


if __name__ == "__main__":
    sys.path.insert(0, os.getcwd())
    sys.exit(main(f"/root/testdata/{(sys.argv[1:] or ['sf0.001'])[0]}", sys.argv[2:]))
