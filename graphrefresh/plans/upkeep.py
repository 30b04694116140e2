"""Keeping long-lived states: what stays in memory, what is evicted, how far sums have drifted."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.models import Model
from graphrefresh.plans import baselines, cost
from graphrefresh.plans.delta import ids
from graphrefresh.plans.full import LayerState, degrees, forward
from graphrefresh.sources.graphs import Batch, Graph, share


def hottest(graph: Graph, fraction: float) -> DataFrame:
    """``vid`` of at least ``fraction`` of the vertices, those with the most in-edges; vertices of one degree stay together."""
    deg = ids(graph.vertices).join(degrees(graph.edges), "vid", "left").select("vid", F.coalesce("deg", F.lit(0.0)).alias("deg"))
    hist = deg.groupBy("deg").agg(F.count(F.lit(1)).alias("n"))
    upto, total = F.sum("n").over(Window.orderBy(F.desc("deg"))), F.sum("n").over(Window.partitionBy(F.lit(1)))
    wanted = hist.select("deg", upto.alias("upto"), total.alias("total")).where(F.col("upto") >= fraction * F.col("total")).agg(F.max("deg").alias("cut"))  # a row a degree
    return deg.join(F.broadcast(wanted), F.col("deg") >= F.col("cut")).select("vid")


def evict(graph: Graph, states: list[LayerState], fraction: float) -> tuple[list[LayerState], list[DataFrame]]:
    """States of the hottest vertices only, and which those are by layer, as refresh asks for."""
    kept = hottest(graph, fraction)
    return [LayerState(s.state.join(kept, "vid", "left_semi"), s.out) for s in states], [kept] * len(states)


def placed(graph: Graph, states: list[LayerState], budget_bytes: int) -> tuple[list[LayerState], str]:
    """States persisted in memory while both tensors, or else the sums, fit the budget; else left in their files."""
    size = {r.layout: r.bytes for r in cost.state_bytes(graph.vertices, states).collect()}  # three rows
    if size["both"] <= budget_bytes:
        return [LayerState(s.state.persist(StorageLevel.MEMORY_AND_DISK), s.out.persist(StorageLevel.MEMORY_AND_DISK)) for s in states], "both"
    if size["sums_only"] <= budget_bytes:
        return [LayerState(s.state.persist(StorageLevel.MEMORY_AND_DISK), s.out) for s in states], "sums_only"
    return states, "files"


def audit(graph: Graph, states: list[LayerState], model: Model, fraction: float, salt: str = "audit") -> DataFrame:
    """``mse, max_abs, vertices``: stored embeddings of a sample against complete recomputation, for a refresh when drift passes a limit."""
    sample = ids(graph.vertices).where(share(salt, F.col("vid")) < fraction)
    none = Batch(graph.edges.limit(0), graph.edges.limit(0), graph.vertices.limit(0), ids(graph.vertices).limit(0))
    exact = baselines.full_neighbour(graph, none, model, sample).embeddings
    return cost.mse(exact, states[-1].out)


def corrected(graph: Graph, states: list[LayerState], model: Model, tolerance: float, fraction: float = 0.01) -> tuple[list[LayerState], bool]:
    """The states, or, where a sample's embeddings are further than ``tolerance`` from exact ones, those of a complete pass; also says which.

    An empty sample, as of an empty graph, shows no drift; a drift that is no number counts as one.
    """
    drift = audit(graph, states, model, fraction).first()
    if drift.vertices == 0 or drift.max_abs <= tolerance:
        return states, False
    return forward(graph, model, write=True), True
