"""Access volumes, their ratios, state sizes and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.plans.delta import KEY, Refresh, union
from graphrefresh.plans.full import LayerState, vector


def traces(runs: dict[str, Refresh]) -> DataFrame:
    """``method, layer, src, dst, rel``: the distinct edges that each method processed in each layer."""
    rows = [t.select(F.lit(m).alias("method"), F.lit(k).alias("layer"), *KEY) for m, r in runs.items() for k, t in enumerate(r.processed, 1)]
    return reduce(DataFrame.unionByName, rows).distinct()


def edge_accesses(trace: DataFrame) -> DataFrame:
    return trace.groupBy("method", "layer").agg(F.count(F.lit(1)).alias("edges"))


def vertex_accesses(trace: DataFrame) -> DataFrame:
    ends = union(trace.select("method", "layer", F.col("src").alias("vid")), trace.select("method", "layer", F.col("dst").alias("vid"))).distinct()
    return ends.groupBy("method", "layer").agg(F.count(F.lit(1)).alias("vertices"))


def normalised(trace: DataFrame, base: str = "delta") -> DataFrame:
    """``method, edges, ratio``: edges over those of the affected subgraph."""
    total = trace.groupBy("method").agg(F.count(F.lit(1)).alias("edges"))
    own = total.where(F.col("method") == base).select(F.col("edges").alias("b"))
    return total.join(F.broadcast(own)).select("method", "edges", (F.col("edges") / F.col("b")).alias("ratio"))  # one row


def redundant_share(trace: DataFrame, base: str = "delta") -> DataFrame:
    """``method, share``: processed edges that are not in the affected subgraph."""
    own = trace.where(F.col("method") == base).select("layer", *KEY, F.lit(1).alias("hit"))
    rows = trace.join(own, ["layer", *KEY], "left")
    return rows.groupBy("method").agg((F.count_if(F.col("hit").isNull()) / F.count(F.lit(1))).alias("share"))


def affected_share(run: Refresh) -> DataFrame:
    """``layer, edge_share, vertex_share`` of the affected subgraph."""
    total = run.graph.edges.agg(F.count(F.lit(1)).alias("e")).join(run.graph.vertices.agg(F.count(F.lit(1)).alias("v")))
    rows = [t.agg(F.count(F.lit(1)).alias("n")).join(c.agg(F.count(F.lit(1)).alias("m"))).join(total).select(F.lit(k).alias("layer"), (F.col("n") / F.col("e")).alias("edge_share"), (F.col("m") / F.col("v")).alias("vertex_share")) for k, (t, c) in enumerate(zip(run.processed, run.changed, strict=True), 1)]
    return reduce(DataFrame.unionByName, rows)


def degree_bands(edges: DataFrame) -> DataFrame:
    """``vid, deg, band``: top 20, middle 30 and bottom 50 per cent of vertices by in-degree.

    Ranks come from the degree histogram, so no task sorts all vertices; a degree's vertices share a band.
    """
    deg = edges.groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("deg"))
    hist = deg.groupBy("deg").agg(F.count(F.lit(1)).alias("n"))
    above = F.coalesce(F.sum("n").over(Window.orderBy(F.desc("deg")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    every = F.sum("n").over(Window.partitionBy(F.lit(1)))
    band = F.when(above < 0.2 * every, "top20").when(above < 0.5 * every, "mid30").otherwise("low50")
    return deg.join(hist.select("deg", band.alias("band")), "deg").select("vid", "deg", "band")


def by_degree_band(trace: DataFrame, edges: DataFrame, less: str, more: str) -> DataFrame:
    """``band, share``: where the edge accesses that ``less`` saves over ``more`` lie, by the destination's degree."""
    rows = trace.where(F.col("method").isin(less, more)).join(degree_bands(edges).withColumnRenamed("vid", "dst"), "dst")
    saved = rows.groupBy("band").agg((F.count_if(F.col("method") == more) - F.count_if(F.col("method") == less)).alias("saved"))
    return saved.select("band", (F.col("saved") / F.sum("saved").over(Window.partitionBy(F.lit(1)))).alias("share"))


def state_bytes(vertices: DataFrame, states: list[LayerState]) -> DataFrame:
    """``layout, bytes``: features and embeddings alone, both tensors of each layer, sums alone."""
    f = vertices.count() * 8 * len(vector(vertices))
    h = sum(s.out.count() * 8 * len(vector(s.out)) for s in states)
    a = sum(s.state.count() * 8 * (len(s.state.columns) - 3) for s in states)
    return vertices.sparkSession.createDataFrame([("features_only", f), ("both", f + h + a), ("sums_only", f + a)], "layout string, bytes long")


def mse(a: DataFrame, b: DataFrame) -> DataFrame:
    """``mse, max_abs, vertices`` over the vertices of ``a``."""
    h = vector(a)
    other = b.select("vid", *[F.col(c).alias(f"o_{c}") for c in h])
    rows = a.join(other, "vid")
    square = sum(((F.col(c) - F.col(f"o_{c}")) ** 2 for c in h), F.lit(0.0))
    return rows.agg((F.avg(square) / len(h)).alias("mse"), F.max(F.greatest(*[F.abs(F.col(c) - F.col(f"o_{c}")) for c in h])).alias("max_abs"), F.count(F.lit(1)).alias("vertices"))


def difference(a: DataFrame, b: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """``max_abs, max_relative, mismatches, vertices``: a vertex mismatches when any component differs by more than ``tolerance`` or it is in one of the two alone."""
    h = vector(a)
    rows = a.withColumn("_a", F.lit(True)).join(b.select("vid", *[F.col(c).alias(f"o_{c}") for c in h], F.lit(True).alias("_b")), "vid", "full")
    gap = [F.abs(F.col(c) - F.col(f"o_{c}")) for c in h]
    apart = F.greatest(*gap, F.lit(0.0))
    relative = F.greatest(*[g / F.greatest(F.abs(F.col(f"o_{c}")), F.lit(1e-12)) for g, c in zip(gap, h, strict=True)], F.lit(0.0))
    alone = F.col("_a").isNull() | F.col("_b").isNull()
    return rows.agg(F.max(apart).alias("max_abs"), F.max(relative).alias("max_relative"), F.count_if(alone | (apart > tolerance)).alias("mismatches"), F.count(F.lit(1)).alias("vertices"))


def label(h: DataFrame) -> DataFrame:
    """``vid, y``: the column with the largest value, the first of equals."""
    names = vector(h)
    best, y = F.greatest(*names), F.lit(len(names) - 1)
    for i in range(len(names) - 2, -1, -1):
        y = F.when(F.col(names[i]) == best, i).otherwise(y)
    return h.select("vid", y.alias("y"))


def accuracy(h: DataFrame, truth: DataFrame) -> DataFrame:
    """``accuracy`` of the embeddings' labels on the labelled vertices."""
    return label(h).join(truth.withColumnRenamed("y", "t"), "vid").agg(F.avg((F.col("y") == F.col("t")).cast("double")).alias("accuracy"))


def analytic(d: float, updated: int, alpha: float, depth: int, fanout_alpha: float) -> dict[str, float]:
    """Edges that each method processes, from mean degree, updated vertices and mean affected fan-out a layer."""
    return {"delta": d * updated * alpha ** (depth + 1), "cache_reuse": d * updated * alpha ** (depth + 2), "full_neighbour": d * updated * alpha ** (2 * depth + 1), "sampled": d * updated * fanout_alpha ** (2 * depth + 1)}


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds until all rows of a refresh are computed."""
    start = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def phases(steps: dict[str, Callable[[], DataFrame]]) -> dict[str, float]:
    """Seconds of each phase. A step does all that the steps before it do, so a phase is what its step takes longer; 0 where the clock's noise is larger than that. All steps run once before to warm up."""
    for step in steps.values():
        timed(step)
    out, before = {}, 0.0
    for name, step in steps.items():
        took = timed(step)
        out[name], before = max(took - before, 0.0), max(took, before)
    return out


def bounded_throughput(seconds: Callable[[int], list[float]], sizes: list[int], bounds: list[float]) -> list[tuple[float, int, float]]:
    """For each latency bound the largest batch all of whose runs keep it, and its worst throughput."""
    runs = {n: seconds(n) for n in sizes}
    out = []
    for bound in bounds:
        ok = [n for n, ts in runs.items() if max(ts) <= bound]
        out.append((bound, max(ok, default=0), max(ok) / max(runs[max(ok)]) if ok else 0.0))
    return out


def throughput(updates: int, seconds: float) -> float:
    """Updated edges a second."""
    return updates / seconds if seconds > 0 else 0.0


def speedup(base_seconds: float, seconds: float) -> float:
    return base_seconds / seconds if seconds > 0 else float("inf")
