import glob
import os

import duckdb
import pytest
from pyspark.sql import SparkSession

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    s = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s


@pytest.fixture(scope="session")
def sql():
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for p in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}{'/*.parquet' if os.path.isdir(p) else ''}'")
    return con


def rows_of(df, columns=None):
    columns = columns or sorted(df.columns)
    return sorted((tuple(str(r[c]) for c in columns) for r in df.collect()), key=str)


def sql_rows(con, query):
    cur = con.execute(query)
    names = [d[0] for d in cur.description]
    order = sorted(names)
    return order, sorted((tuple(str(r[names.index(c)]) for c in order) for r in cur.fetchall()), key=str)
