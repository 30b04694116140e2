"""Operators over unbounded streams: running sums of the first layer, and events matched with later ones."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphrefresh.models import Layer
from graphrefresh.plans.full import messages, sources


def layer_one_sums(changes: DataFrame, features: DataFrame, layer: Layer, salts: int = 16) -> DataFrame:
    """``vid, salt, s0.., n``: after each micro-batch the running sums of the vertices it touched, from a stream of edges (src, dst, rel, w, sign) with sign 1 for a new and -1 for a deleted edge.

    For layers that add up what depends on the source alone. A vertex's sums are kept in ``salts`` parts by the source, so
    that no task takes all edges of a hub; ``whole_sums`` adds the parts up. State is a row of numbers a part. Edges
    whose source has no features count nothing; a null sign counts as 1; with no edge left in a part its sums are exactly 0.
    """
    if layer.reads_target or layer.reads_degree or layer.per_relation or layer.combine_by != "sum":
        raise ValueError("only sums of messages that depend on the source alone can be kept from a stream of edges")
    names = [f"s{i}" for i in range(layer.state_width)]
    salted = changes.withColumn("salt", F.pmod(F.xxhash64("src"), F.lit(salts)).cast("int")).withColumn("sign", F.coalesce(F.col("sign").cast("double"), F.lit(1.0)))
    rows = messages(salted, sources(features, layer), None, layer, "salt", "sign")
    signed = rows.selectExpr("dst AS vid", "salt", *[f"c{i} * sign AS s{i}" for i in range(layer.state_width)], "sign AS n")

    def add(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = list(state.get) if state.exists else [0.0] * (len(names) + 1)
        for rows in batches:
            total = [float(t + x) for t, x in zip(total, rows[[*names, "n"]].sum(), strict=True)]
        if total[-1] == 0:
            total = [0.0] * len(total)
            state.remove()
        else:
            state.update(tuple(total))
        yield pd.DataFrame([[*key, *total[:-1], int(total[-1])]], columns=["vid", "salt", *names, "n"])

    sums = ", ".join(f"{c} double" for c in names)
    return signed.groupBy("vid", "salt").applyInPandasWithState(add, f"vid long, salt int, {sums}, n long", f"{sums}, n double", "update", GroupStateTimeout.NoTimeout)


def whole_sums(parts: DataFrame, order: str) -> DataFrame:
    """``vid, s0.., n`` from the parts of all micro-batches, of which ``order`` tells the later: a part's last row holds."""
    names = [c for c in parts.columns if c not in ("vid", "salt", order)]
    last = parts.groupBy("vid", "salt").agg(F.max_by(F.struct(*names), order).alias("x"))
    return last.groupBy("vid").agg(*[F.sum(f"x.{c}").alias(c) for c in names]).where("n <> 0")


def followed(first: DataFrame, then: DataFrame, key: str, within: str = "1 hour", late: str = "10 minutes", how: str = "inner") -> DataFrame:
    """``key, at, then_at``: events of a stream with those of another of the same key up to ``within`` later; ``how`` "leftOuter" keeps those that none follows, once the watermark says so.

    Both streams have ``key`` and ``ts``; rows later than ``late`` are dropped by the watermark, which bounds what is kept. Null keys match nothing.
    """
    a = first.select(F.col(key), F.col("ts").alias("at")).withWatermark("at", late)
    b = then.select(F.col(key).alias("_key"), F.col("ts").alias("then_at")).withWatermark("then_at", late)
    return a.join(b, F.expr(f"{key} = _key AND then_at >= at AND then_at <= at + INTERVAL {within}"), how).drop("_key")
