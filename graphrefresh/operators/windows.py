"""Orders and windows over whole tables without a task that holds them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def ranked(df: DataFrame, coarse: Column, *order: str | Column, name: str = "rank") -> DataFrame:
    """``df`` with its place (from 0) in the order (coarse, order). ``coarse`` must rise with the order; a window sees one value of it, and one row for each of the others."""
    rows = df.withColumn("_c", coarse)
    counts = rows.groupBy("_c").agg(F.count(F.lit(1)).alias("_n"))
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inside = F.row_number().over(Window.partitionBy("_c").orderBy(*order)) - 1
    return rows.withColumn("_i", inside).join(counts.select(F.col("_c").alias("_d"), before.alias("_before")), F.col("_c").eqNullSafe(F.col("_d"))).withColumn(name, F.col("_before") + F.col("_i")).drop("_c", "_d", "_i", "_before")


def batches(df: DataFrame, n: int, coarse: Column, *order: str | Column) -> DataFrame:
    """``df`` in ``n`` batches of equal size (column ``batch``), by order."""
    total = df.agg(F.count(F.lit(1)).alias("_t"))  # one row
    placed = ranked(df, coarse, *order, name="_r").join(F.broadcast(total))
    return placed.withColumn("batch", F.floor(F.col("_r") * n / F.col("_t"))).drop("_r", "_t")


def sessions(df: DataFrame, key: str, at: str, gap: str) -> DataFrame:
    """``key, start, last, n``: rows of a key no further apart than ``gap``; streams take it as well as tables."""
    return df.groupBy(key, F.session_window(at, gap).alias("w")).agg(F.min(at).alias("start"), F.max(at).alias("last"), F.count(F.lit(1)).alias("n")).drop("w")


def top_per(df: DataFrame, key: str, k: int, *order: str | Column) -> DataFrame:
    """The first k rows of each key; the window's limit is pushed below the shuffle by the optimizer."""
    return df.withColumn("place", F.row_number().over(Window.partitionBy(key).orderBy(*order))).where(F.col("place") <= k)


#: Functions for SQL users, as (name, parameters, result, body).
SQL_FUNCTIONS = (
    ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0e0, (s, v) -> s + v)"),
    ("vec_add", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> x + y)"),
    ("vec_scale", "a ARRAY<DOUBLE>, f DOUBLE", "ARRAY<DOUBLE>", "transform(a, x -> f * x)"),
    ("leaky_relu", "x DOUBLE", "DOUBLE", "CASE WHEN x > 0 THEN x ELSE 0.2e0 * x END"),
)


def register_functions(spark: SparkSession) -> None:
    """Make the vector functions known to SQL; they are inlined into plans, so they stay in generated code."""
    for name, parameters, result, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {result} RETURN {body}")
