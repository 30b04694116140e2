"""Helpers shared by the training-data operators."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh.plans.cut import work_dir

#: A word is a maximal run of anything but blank and the five ASCII line/tab controls.
BLANK = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
#: The same six characters, for translate().
BLANK_CHARS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def words_of(text: Column) -> Column:
    """Array of the words of a text; a null text has none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANK, -1), lambda w: w != "")


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once and hand it to ``body`` as a lambda variable, so that nested lambdas don't repeat it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def work_path(spark: SparkSession, label: str) -> str:
    """A new folder that the driver and all executors share, deleted with the application's others when the driver ends."""
    return f"{work_dir(spark)}/{label}-{uuid.uuid4().hex}"


def unused(name: str, *frames: DataFrame) -> str:
    """``name``, or a longer one where a frame has a column of that name."""
    taken = {c.lower() for f in frames for c in f.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def written(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage with a Parquet table in the shared folder."""
    path = work_path(df.sparkSession, label)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
