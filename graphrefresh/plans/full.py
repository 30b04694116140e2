"""Whole-graph forward pass: messages, one aggregate per destination for context and sum together, finish, update."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.functions.weights import mapped
from graphrefresh.models import WIDTH, Layer, Model
from graphrefresh.plans.cut import beside, cut
from graphrefresh.sources.graphs import Graph

#: Columns of the zoo's embeddings.
H = [f"h{i}" for i in range(WIDTH)]


@dataclass(frozen=True)
class LayerState:
    """``state``: vid, rk, s0.., n (the sums, the in-edges they hold); ``out``: vid, h0.. (the layer's embeddings)."""

    state: DataFrame
    out: DataFrame


def vector(h: DataFrame) -> list[str]:
    """The columns of an embedding."""
    return [c for c in h.columns if c != "vid"]


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).cast("double").alias("deg"))


def sources(h: DataFrame, layer: Layer, *keep: str) -> DataFrame:
    """``src, q0..`` and ``keep``: what each vertex contributes to its out-edges; ``h`` has ``deg`` too where the layer reads it."""
    return mapped(h, layer.source_maps).selectExpr("vid AS src", *_as("q", layer.source), *keep)


def targets(h: DataFrame, layer: Layer) -> DataFrame:
    """``dst, p0..``: what each vertex contributes to its in-edges."""
    return mapped(h, layer.target_maps).selectExpr("vid AS dst", *_as("p", layer.target))


def _as(prefix: str, expressions: list[str]) -> list[str]:
    return [f"{x} AS {prefix}{i}" for i, x in enumerate(expressions)]


def with_degree(h: DataFrame, degree: DataFrame) -> DataFrame:
    return h.join(degree, "vid", "left").withColumn("deg", F.expr("coalesce(deg, 0e0)"))


def messages(edges: DataFrame, q: DataFrame, p: DataFrame | None, layer: Layer, *keep: str) -> DataFrame:
    """``dst, rk, c0..`` and ``keep``: one row per edge and row of q. The destination is joined only where messages read it. Edges in chunks take q by chunk."""
    rows = beside(edges).join(beside(q), ["chunk", "src"] if "chunk" in edges.columns else "src")
    if layer.reads_target:
        rows = beside(rows).join(beside(p), "dst")
    return rows.selectExpr("dst", ("rel" if layer.per_relation else "''") + " AS rk", *_as("c", layer.message), *keep)


def fold(rows: DataFrame, layer: Layer, signed: bool = False) -> DataFrame:
    """``vid, rk, s0.., n`` by destination; sums combine map-side, which takes in the in-edges of a hub. Rows of negative ``sign`` count against n and are no candidates for an extreme."""
    if layer.combine_by == "sum":
        folds = [f"sum(c{i} * sign)" if signed else f"sum(c{i})" for i in range(layer.state_width)]
    else:
        folds = [f"{layer.combine_by}(CASE WHEN sign > 0 THEN c{i} END)" if signed else f"{layer.combine_by}(c{i})" for i in range(layer.state_width)]
    n = "CAST(sum(sign) AS BIGINT)" if signed else "count(1)"
    return rows.withColumnRenamed("dst", "vid").groupBy("vid", "rk").agg(*[F.expr(x) for x in [*_as("s", folds), f"{n} AS n"]])


def summed(edges: DataFrame, h: DataFrame, layer: Layer, degree: DataFrame | None) -> DataFrame:
    """The state that the edges make with the embeddings ``h`` of their ends."""
    q = sources(with_degree(h, degree) if layer.reads_degree else h, layer)
    return fold(messages(edges, q, targets(h, layer) if layer.reads_target else None, layer), layer)


def finish(state: DataFrame, layer: Layer, *keep: str) -> DataFrame:
    """``vid, a0..`` and ``keep``: the context applied to the sums, relations added up (then nothing is kept)."""
    rows = state.selectExpr("vid", *keep, *_as("a", layer.finish))
    return rows.groupBy("vid").agg(*[F.expr(f"sum(a{i}) AS a{i}") for i in range(layer.sums)]) if layer.per_relation else rows


def output(h: DataFrame, a: DataFrame, layer: Layer, *keep: str) -> DataFrame:
    """``vid, h0..`` and ``keep`` of every vertex of ``h``; one without in-edges has a zero aggregate. Only updates that read the vertex's own embedding need more than its id."""
    rows = h.join(beside(a), "vid", "left").selectExpr(*h.columns, *keep, *[f"coalesce(a{i}, 0e0) AS a{i}" for i in range(layer.sums)])
    return mapped(rows, layer.update_maps).selectExpr("vid", *keep, *_as("h", layer.update))


def forward(graph: Graph, model: Model, reorder: bool = True, write: bool = False) -> list[LayerState]:
    """States of all layers; ``write`` settles each as a table before the next layer reads it. ``reorder`` False joins the context back to the edges and applies it before the sum, for comparison."""
    settle = (lambda df: cut(df, probed=True)) if write else lambda df: df
    h, degree, states = graph.vertices, degrees(graph.edges), []
    for layer in model.layers:
        state = settle(summed(graph.edges, h, layer, degree) if reorder else _unordered(graph.edges, h, layer, degree))
        h = settle(output(h, finish(state, layer) if reorder else state, layer))
        states.append(LayerState(state, h))
    return states


def _unordered(edges: DataFrame, h: DataFrame, layer: Layer, degree: DataFrame) -> DataFrame:
    """Context first, back to every edge, combined there, then summed: an edge-sized join more."""
    q = sources(with_degree(h, degree) if layer.reads_degree else h, layer)
    rows = messages(edges, q, targets(h, layer) if layer.reads_target else None, layer)
    named = rows.select("dst", "rk", *[F.col(f"c{i}").alias(f"s{i}") for i in range(layer.sums)])
    if layer.contexts:
        context = rows.groupBy(F.col("dst").alias("d"), F.col("rk").alias("r")).agg(*[F.sum(f"c{i}").alias(f"s{i}") for i in range(layer.sums, layer.state_width)])
        named = named.join(context, (F.col("dst") == F.col("d")) & (F.col("rk") == F.col("r")))
    each = named.select(F.col("dst").alias("vid"), *[F.expr(x).alias(f"a{i}") for i, x in enumerate(layer.finish)])
    return each.groupBy("vid").agg(*[F.sum(f"a{i}").alias(f"a{i}") for i in range(layer.sums)])


def rebuilt(vertices: DataFrame, states: list[LayerState], model: Model) -> list[LayerState]:
    """States whose embeddings are made anew from the stored sums, for a layout that keeps sums alone: no edge is read."""
    h, out = vertices, []
    for layer, kept in zip(model.layers, states, strict=True):
        h = output(h, finish(kept.state, layer), layer)
        out.append(LayerState(kept.state, h))
    return out
