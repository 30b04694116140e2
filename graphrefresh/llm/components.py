"""Connected components of an edge table by alternating stars; every round is a written table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.llm.common import written


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """Tie each node's neighbours to its least neighbour: larger ones in a large star, smaller ones and the node itself in a small one."""
    if large:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), F.least("u", "m").alias("m"))
    near = both.join(least, F.col("u") == F.col("c"))
    out = near.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")) if large else near.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select(F.col("c").alias("u"), F.col("m").alias("v")))
    return out.where(F.col("u") != F.col("v")).distinct()


def components(edges: DataFrame) -> DataFrame:
    """``node, root`` for every node of the edges (u, v), root being the least node it is connected with.

    Rounds go on until the edges no longer change; a node's edges are aggregated before and after each shuffle and never
    gathered. Only a count and a checksum come to the driver.
    """
    edges = written(edges.where(F.col("u") != F.col("v")).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "edges")
    mark = None
    while True:
        now = edges.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(u, v))")).first()
        if now == mark or not now[0]:
            break
        mark = now
        edges = written(_stars(_stars(edges, True), False), "edges")
    roots = edges.groupBy(F.greatest("u", "v").alias("node")).agg(F.min(F.least("u", "v")).alias("root"))
    return roots.unionByName(roots.select(F.col("root").alias("node"), F.col("root")).distinct())
