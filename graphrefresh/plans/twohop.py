"""The two-hop relation of a graph with path counts, kept under edge changes by signed joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.plans.delta import union


def _paths(first: DataFrame, second: DataFrame) -> DataFrame:
    """``src, dst, n`` of the products of multiplicities along first, then second."""
    a = first.select("src", F.col("dst").alias("mid"), F.col("n").alias("n1"))
    b = second.select(F.col("src").alias("mid"), "dst", F.col("n").alias("n2"))
    return a.join(b, "mid").groupBy("src", "dst").agg(F.sum(F.col("n1") * F.col("n2")).alias("n"))


def counted(edges: DataFrame) -> DataFrame:
    """``src, dst, n``: parallel edges as a multiplicity."""
    return edges.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def two_hop(edges: DataFrame) -> DataFrame:
    """``src, dst, n``: the pairs that a path of two edges joins and the number of such paths."""
    own = counted(edges)
    return _paths(own, own)


def signed_changes(inserted: DataFrame, deleted: DataFrame) -> DataFrame:
    """``src, dst, n`` of a batch, n negative where more edges go than come."""
    rows = union(inserted.select("src", "dst", F.lit(1).cast("long").alias("s")), deleted.select("src", "dst", F.lit(-1).cast("long").alias("s")))
    return rows.groupBy("src", "dst").agg(F.sum("s").alias("n")).where("n <> 0")


def two_hop_delta(old: DataFrame, paths: DataFrame, inserted: DataFrame, deleted: DataFrame) -> DataFrame:
    """The two-hop relation after a batch, from the relation before it: only paths with a changed edge are joined.

    With A the old and D the change, (A + D)(A + D) - AA is D A + A D + D D. A pair whose count falls to 0 is gone.
    """
    a, d = counted(old), signed_changes(inserted, deleted)
    rows = union(paths.select("src", "dst", "n"), _paths(d, a), _paths(a, d), _paths(d, d))
    return rows.groupBy("src", "dst").agg(F.sum("n").alias("n")).where("n <> 0")
