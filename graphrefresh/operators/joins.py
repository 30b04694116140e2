"""Joins that the built-in ones don't offer: as-of, within an interval, nearest neighbours, checked broadcast."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A side is broadcast up to this many rows.
BROADCAST_ROWS = 100_000


def checked_broadcast(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if it has no more than ``rows`` rows, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def as_of(left: DataFrame, right: DataFrame, key: str, order: str, value: str, width: int) -> DataFrame:
    """``left`` with ``value`` of the last row of ``right`` of the same key whose ``order`` is less; null where none is.

    Both sides become one ordered sequence, so there is no inequality join. It is cut every ``width`` of ``order``: a
    task holds a key's rows of one stretch, and what earlier stretches hand on is one row each, so a hot key is spread.
    """
    seen = right.select(key, order, F.struct(F.col(value).alias("v")).alias("_r"), F.lit(1).alias("_side"))
    rows = left.withColumns({"_l": F.struct("*"), "_side": F.lit(0)}).select(key, order, "_l", "_side").unionByName(seen, allowMissingColumns=True)
    rows = rows.withColumn("_b", F.floor(F.col(order) / width))
    inside = F.last("_r", ignorenulls=True).over(Window.partitionBy(key, "_b").orderBy(order, "_side").rowsBetween(Window.unboundedPreceding, -1))
    ends = seen.withColumn("_b", F.floor(F.col(order) / width)).groupBy(key, "_b").agg(F.max_by("_r", order).alias("_e"))
    stretches = rows.select(F.col(key).alias("_k"), F.col("_b").alias("_c")).distinct()
    ends = ends.join(stretches, F.col(key).eqNullSafe(F.col("_k")) & F.col("_b").eqNullSafe(F.col("_c")), "right")
    handed = F.last("_e", ignorenulls=True).over(Window.partitionBy("_k").orderBy("_c").rowsBetween(Window.unboundedPreceding, -1))
    carried = ends.select("_k", "_c", handed.alias("_before"))
    same = F.col(key).eqNullSafe(F.col("_k")) & F.col("_b").eqNullSafe(F.col("_c"))
    out = rows.withColumn("_in", inside).where("_side = 0").join(carried, same, "left")
    return out.select("_l.*", F.coalesce("_in", "_before")["v"].alias(value))


def within(left: DataFrame, right: DataFrame, key: str, at: str, before: int) -> DataFrame:
    """Pairs of the same key where right's ``at`` lies in [left's at - before, left's at]; right's columns get the suffix _r.

    Each left row looks into two stretches of length ``before``, so the join is by equality and the interval is a filter.
    """
    stretch = F.floor(F.col(at) / before)
    l = left.withColumn("_b", F.explode(F.array(stretch - 1, stretch)))
    r = right.select(*[F.col(c).alias(f"{c}_r") for c in right.columns], F.col(key).alias("_k"), stretch.alias("_c"))
    gap = F.col(at) - F.col(f"{at}_r")
    return l.join(r, (F.col(key) == F.col("_k")) & (F.col("_b") == F.col("_c"))).where((gap >= 0) & (gap <= before)).drop("_b", "_k", "_c")


def nearest(vectors: DataFrame, k: int, block_rows: int = 4096, digits: int = 9) -> DataFrame:
    """``query, vec_id, similarity, rank``: the k nearest others of every row of ``vectors`` (vec_id, embedding) by cosine, exactly.

    Vectors are dealt to blocks; a task compares two blocks by one matrix product and gives k rows a query, which are
    merged by a window. Work is quadratic, rows and memory are not: no pair is ever a row. Similarities are rounded
    before ranking, so that ties fall to the lesser id.
    """
    blocks = max(1, -(-vectors.count() // block_rows))
    dealt = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("x"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("own"))
    other = dealt.withColumn("side", F.lit(1)).withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumnRenamed("own", "c")
    query = dealt.withColumn("side", F.lit(0)).withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumnRenamed("own", "q")

    def compare(rows: pd.DataFrame) -> pd.DataFrame:
        a, b = rows[rows.side == 0], rows[rows.side == 1]
        if a.empty or b.empty:
            return pd.DataFrame({"query": [], "vec_id": [], "similarity": []})
        unit = lambda m: m / np.where((n := np.linalg.norm(m, axis=1, keepdims=True)) > 0, n, 1.0)
        s = np.round(unit(np.stack(a.x)) @ unit(np.stack(b.x)).T, digits)
        ids, out = b.vec_id.to_numpy(), []
        for i, q in enumerate(a.vec_id.to_numpy()):
            s[i, ids == q] = -np.inf
            best = np.lexsort((ids, -s[i]))[:k]
            out.append(pd.DataFrame({"query": q, "vec_id": ids[best], "similarity": s[i, best]}))
        found = pd.concat(out)
        return found[np.isfinite(found.similarity)]

    found = query.unionByName(other).groupBy("q", "c").applyInPandas(compare, "query long, vec_id long, similarity double")
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("similarity"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k)


def matmul(df: DataFrame, column: str, weights: list[list[float]], out: str = "out") -> DataFrame:
    """``df`` with ``column`` (vectors as arrays) times a fixed matrix, a batch at a time, for wide layers."""
    from pyspark.sql.types import ArrayType, DoubleType, StructField, StructType

    schema, w = StructType([*df.schema.fields, StructField(out, ArrayType(DoubleType()))]), np.array(weights, float)

    def run(batches: Iterable[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            x = np.stack(b[column]).astype(float) if len(b) else np.zeros((0, w.shape[1]))
            yield b.assign(**{out: list(x @ w.T)})

    return df.mapInPandas(run, schema)


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays; 0 where one has no length."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, v: s + v)
    length = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(length > 0, dot(a, b) / length).otherwise(0.0)


def vector_sum(df: DataFrame, key: str, column: str) -> DataFrame:
    """``key, pos, total``: element-wise sums of arrays, combined map-side."""
    return df.select(key, F.posexplode(column).alias("pos", "x")).groupBy(key, "pos").agg(F.sum(F.col("x").cast("double")).alias("total"))
