"""Chunked execution: edges dealt to chunks by destination, source vectors loaded once a chunk or once for neighbouring chunks, and what that loads."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.plans.cut import beside
from graphrefresh.plans.cut import cut as written


def plan(edges: DataFrame, max_edges: int = 8192) -> DataFrame:
    """The edges and their ``chunk``: whole destinations in order of id, cut about every ``max_edges`` in-edges.

    Running sums go over blocks of 1024 ids and then inside a block, so no task sees all destinations.
    """
    per = edges.groupBy("dst").agg(F.count(F.lit(1)).alias("n")).withColumn("b", F.floor(F.col("dst") / 1024))
    blocks = per.groupBy("b").agg(F.sum("n").alias("s"))
    before = F.coalesce(F.sum("s").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("b").orderBy("dst").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    cut = per.join(blocks.select("b", before.alias("before")), "b").select("dst", F.floor((F.col("before") + inside) / max_edges).alias("chunk"))
    return edges.join(cut, "dst").select(*edges.columns, "chunk")


def loads(chunks: DataFrame) -> DataFrame:
    """``loads, shared_loads``: source vectors loaded by all chunks, and those left when a chunk takes over what the one before has."""
    own = chunks.select("chunk", "src").distinct()
    before = F.lag("chunk").over(Window.partitionBy("src").orderBy("chunk"))
    return own.select((F.col("chunk") == before + 1).alias("kept")).agg(F.count(F.lit(1)).alias("loads"), F.count_if(~F.coalesce("kept", F.lit(False))).alias("shared_loads"))


def sharing(chunks: DataFrame) -> DataFrame:
    """``chunk_a, chunk_b, shared``: sources that neighbouring chunks have in common."""
    own = chunks.select("chunk", "src").distinct()
    nxt = own.select((F.col("chunk") - 1).alias("chunk"), "src")
    return own.join(nxt, ["chunk", "src"]).groupBy(F.col("chunk").alias("chunk_a")).agg(F.count(F.lit(1)).alias("shared")).select("chunk_a", (F.col("chunk_a") + 1).alias("chunk_b"), "shared")


def dealt(edges: DataFrame, q: DataFrame, max_edges: int = 8192, together: int = 1) -> tuple[DataFrame, DataFrame]:
    """Edges and source contributions by chunk, to be joined on (chunk, src): a contribution goes once to every ``together`` neighbouring chunks that read it, however many of their edges do.

    A source that many edges read is thereby spread over chunks, so no task holds all out-edges of a hub.
    """
    rows = written(plan(edges, max_edges).withColumn("chunk", F.floor(F.col("chunk") / together)))
    return rows, beside(rows.select("chunk", "src").distinct()).join(beside(q), "src")
