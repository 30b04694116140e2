"""Incremental refresh: signed messages of the affected edges update stored sums; everything else is kept and not read.

Rules for which edges are affected at a layer:
- edges that appear or disappear count at every layer; one that does both ways (a changed source too) counts once a side;
- all out-edges of vertices whose embedding below changed, or, for messages that read the source's degree, whose degree did;
- where messages read the destination, every destination whose embedding below changed is summed anew over all in-edges;
- where the update reads the vertex's own embedding, a vertex that changed below changes here too.

What changed at a layer is a small written table of vertices with their old and new embeddings. Edges, states and
embeddings are looked up by such tables' ids, so the work follows the change; only a caller who asks for the whole new
graph or for all embeddings makes Spark read everything.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.models import Layer, Model
from graphrefresh.plans import chunk
from graphrefresh.plans.cut import beside, cut
from graphrefresh.plans.full import LayerState, finish, fold, messages, output, sources, summed, targets, vector
from graphrefresh.sources.graphs import Batch, Graph, apply, expanded, out_of

KEY = ["src", "dst", "rel"]
EDGE = [*KEY, "w"]


def ids(df: DataFrame, column: str = "vid") -> DataFrame:
    return df.selectExpr(f"{column} AS vid")


def union(*frames: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def at(rows: DataFrame, vertices: DataFrame) -> DataFrame:
    return out_of(rows, vertices, "vid")


def outside(rows: DataFrame, vertices: DataFrame | None, side: str = "dst") -> DataFrame:
    return rows if vertices is None else rows.join(beside(vertices.selectExpr("vid AS _k")), F.expr(f"{side} = _k"), "left_anti")


def replaced(old: DataFrame, new: DataFrame, gone: DataFrame) -> DataFrame:
    """Rows of ``old`` with those of ``new`` over them and those of ``gone`` away."""
    return outside(old, union(ids(new), ids(gone)), "vid").unionByName(new.select(*old.columns))


def lacking(edges: DataFrame, deleted: DataFrame) -> DataFrame:
    return edges.join(beside(deleted.selectExpr("src AS _s", "dst AS _d", "rel AS _r")), F.expr("src = _s AND dst = _d AND rel = _r"), "left_anti")


class Frames:
    """Lookups in a graph and its states that are given as whole tables: a small table of ids is broadcast to them."""

    def __init__(self, graph: Graph, states: list[LayerState], complete: bool = True):
        self.graph, self.states, self.complete = graph, states, complete

    def out_edges(self, of: DataFrame) -> DataFrame:
        return out_of(self.graph.edges, of)

    def in_edges(self, of: DataFrame) -> DataFrame:
        return out_of(self.graph.edges, of, "dst")

    def out(self, k: int, of: DataFrame) -> DataFrame:
        """Embeddings of layer ``k``, counted from 1; 0 are the features."""
        return at(self.graph.vertices if k == 0 else self.states[k - 1].out, of)

    def state(self, k: int, of: DataFrame) -> DataFrame:
        return at(self.states[k - 1].state, of)

    def degrees(self, of: DataFrame) -> DataFrame:
        """In-degrees: the first layer's states know how many in-edges they hold; where some are missing, edges are counted."""
        rows = self.state(1, of) if self.complete else self.in_edges(of).select(F.col("dst").alias("vid"), F.lit(1).alias("n"))
        return rows.groupBy("vid").agg(F.sum("n").cast("double").alias("deg"))


@dataclass(frozen=True)
class Change:
    """What a batch does to a layer: ``state`` replaces all stored rows of the vertices in ``touched``; ``front`` has, for each changed vertex, the old embedding (o0.., null for a new one) and the new one (h0..)."""

    touched: DataFrame
    state: DataFrame
    front: DataFrame

    @property
    def out(self) -> DataFrame:
        return self.front.select("vid", *_new(self.front))


@dataclass(frozen=True)
class Refresh:
    """The graph and states after a batch, planned when they are asked for; by layer the vertices that changed and the edges that were processed."""

    graph_of: Callable[[], Graph]
    states_of: Callable[[], list[LayerState]]
    changed: list[DataFrame]
    processed_of: Callable[[], list[DataFrame]]
    changes: list[Change] | None = None

    @cached_property
    def graph(self) -> Graph:
        return self.graph_of()

    @cached_property
    def states(self) -> list[LayerState]:
        return self.states_of()

    @cached_property
    def processed(self) -> list[DataFrame]:
        return self.processed_of()

    @property
    def embeddings(self) -> DataFrame:
        return self.states[-1].out


def _new(front: DataFrame) -> list[str]:
    return [c for c in front.columns if c[0] == "h"]


def _fronted(new: DataFrame, old: DataFrame) -> DataFrame:
    return new.join(beside(old.selectExpr("vid", *[f"{c} AS o{c[1:]}" for c in vector(old)])), "vid", "left")


def _sums(layer: Layer) -> list[str]:
    return [f"s{i}" for i in range(layer.state_width)]


def _state(layer: Layer) -> list[str]:
    return ["rk", *_sums(layer), "n"]


def _degrees(old: Frames, of: DataFrame, by_degree: DataFrame) -> DataFrame:
    """``vid, deg_old, deg_new``: in-degrees of the vertices before and after the batch."""
    rows = of.distinct().join(beside(old.degrees(of)), "vid", "left").join(beside(by_degree), "vid", "left")
    return rows.selectExpr("vid", "coalesce(deg, 0e0) AS deg_old", "coalesce(deg, 0e0) + coalesce(d, 0e0) AS deg_new")


def merge(state: DataFrame, change: DataFrame, layer: Layer) -> DataFrame:
    """Stored sums plus changes; with no in-edge left the sums are exactly 0, whatever rounding left in them."""
    rows = union(state, change).groupBy("vid", "rk").agg(*[F.expr(f"{layer.combine_by}({s}) AS {s}") for s in _sums(layer)], F.expr("sum(n) AS n"))
    return rows.where("n <> 0")


def refresh_from(old: Frames, b: Batch, model: Model, *, need: list[DataFrame] | None = None, prune: bool = False, reorder: bool = True, stored: list[DataFrame] | None = None, contextual: bool = False, chunks: tuple[int, int] | None = None) -> tuple[list[Change], Callable[[], list[DataFrame]]]:
    """By layer what an expanded batch changes, and (when called) the edges that were processed. See ``refresh`` for the options."""
    front = _fronted(b.changed, old.out(0, b.changed))
    if (stored is not None or any(x.combine_by != "sum" for x in model.layers)) and not b.changed.isEmpty():
        # read up to nine times in the first layer, its joins each time
        front = cut(front)
    fresh = ids(front.where(f"o{vector(b.changed)[0][1:]} IS NULL"))
    moved = union(b.inserted.selectExpr("src", "dst", "1 AS d"), b.deleted.selectExpr("src", "dst", "-1 AS d"))
    ends, seeds, by_degree = ids(moved, "dst"), ids(moved, "src"), None
    if any(x.reads_degree for x in model.layers):
        by_degree = cut(moved.groupBy(F.col("dst").alias("vid")).agg(F.sum("d").cast("double").alias("d")))
    changes, traces = [], []
    for k, layer in enumerate(model.layers, 1):
        within = lambda edges, k=k: edges if need is None else out_of(edges, need[k], "dst")
        moving = lambda edges, kind, within=within: within(edges).selectExpr(*EDGE, f"{kind} AS kind")
        touched, known = (union(ids(front), ends), union(seeds, ends)) if layer.reads_degree else (ids(front), seeds)
        aff = union(lacking(within(old.out_edges(touched)), b.deleted).selectExpr(*EDGE, "0 AS kind"), moving(b.deleted, -1), moving(b.inserted, 1))
        q = _both(old, k, layer, front, known, by_degree)
        if layer.combine_by != "sum" or stored is not None:
            # read several times below: in one plan with all that reads them, planning alone would fill the driver's heap
            aff, q = cut(aff), cut(q)
        redo = [ids(front)] if layer.reads_target else []
        if not reorder and layer.contexts:
            redo.append(ends)
        if stored is not None:
            redo.append(outside(union(ids(aff, "dst"), *([ids(front)] if layer.self_term else [])), stored[k - 1], "vid"))
        if layer.combine_by != "sum":
            redo.append(cut(_extremes_lost(aff, q, old, k, layer, contextual)))
        again = None
        if redo:
            again = union(*redo)
            again = cut((again if need is None else at(again, need[k])).distinct())
        part = outside(aff, again)
        if layer.reads_target:
            part = cut(part)
        p = targets(old.out(k - 1, ids(part, "dst")), layer) if layer.reads_target else None
        dealt, given = (part, q) if chunks is None else chunk.dealt(part, q, *chunks)
        change = cut(fold(messages(dealt, given, p, layer, "kind", "sign").where("kind * sign >= 0"), layer, signed=True))
        hit = union(ids(change), fresh, *([ids(front)] if layer.self_term else []), *([again] if again is not None else []))
        affected = outside(hit, b.removed, "vid")
        affected = (affected if need is None else at(affected, need[k])).distinct()
        stale = old.state(k, hit)
        state = merge(outside(strip_context(stale, layer) if contextual else stale, again, "vid"), change, layer)
        below, edges = front.select("vid", *_new(front)), None
        if again is not None:
            edges = cut(union(lacking(old.in_edges(again), b.deleted).select(*EDGE), out_of(b.inserted, again, "dst").select(*EDGE)))
            both = union(ids(edges, "src"), again)
            degree = _degrees(old, both, by_degree).selectExpr("vid", "deg_new AS deg") if layer.reads_degree else None
            state = cut(union(state, summed(edges, replaced(old.out(k - 1, both), below, b.removed), layer, degree)))
        base = at(replaced(old.out(k - 1, hit), below, b.removed), affected) if layer.self_term else affected
        if layer.per_relation:
            state = state if again is not None else cut(state)
            front = cut(_fronted(output(base, finish(state, layer), layer), old.out(k, hit)))
        else:
            one = cut(_fronted(output(base, finish(state, layer, *_state(layer)), layer, *_state(layer)), old.out(k, hit)))
            state, front = one.where("n IS NOT NULL").select("vid", *_state(layer)), one.select("vid", *[c for c in one.columns if c[0] in "ho"])
        if prune:
            front = front.where(" OR ".join(f"NOT (h{i} <=> o{i})" for i in range(len(layer.update))))
        changes.append(Change(union(hit, ids(b.removed)), with_context(state, layer) if contextual else state, front))
        traces.append((part, edges))
    return changes, lambda: [(x.select(*KEY) if y is None else union(x.select(*KEY), y.select(*KEY))).distinct() for x, y in traces]


def _both(old: Frames, k: int, layer: Layer, front: DataFrame, known: DataFrame, by_degree: DataFrame | None) -> DataFrame:
    """``src, q0.., sign``: what changed vertices and the ``known`` unchanged ones contribute to layer ``k`` before (-1) and after the batch (1)."""
    h = _new(front)
    still = outside(old.out(k - 1, known), front, "vid").selectExpr("vid", *h, *[f"{c} AS o{c[1:]}" for c in h])
    rows, names, before, after = union(front, still), list(h), [f"o{c[1:]}" for c in h], list(h)
    if layer.reads_degree:
        rows = rows.join(beside(_degrees(old, union(ids(front), known), by_degree)), "vid", "left")
        names, before, after = [*names, "deg"], [*before, "coalesce(deg_old, 0e0)"], [*after, "coalesce(deg_new, 0e0)"]
    rows = rows.selectExpr("vid", f"stack(2, -1e0, {', '.join(before)}, 1e0, {', '.join(after)}) AS (sign, {', '.join(names)})")
    return sources(rows, layer, "sign")


def refresh(old: Graph, states: list[LayerState], b: Batch, model: Model, *, need: list[DataFrame] | None = None, prune: bool = False, reorder: bool = True, stored: list[DataFrame] | None = None, contextual: bool = False, chunks: tuple[int, int] | None = None) -> Refresh:
    """Embeddings after a batch, equal to those of a forward pass over the new graph.

    ``need`` restricts layer l to need[l] (see on_demand). ``prune`` drops vertices whose value came out as it was.
    ``reorder`` False does without the separation of context and sum: every destination whose in-edges changed is summed
    anew. ``stored`` names, by layer, the vertices whose sums are kept; others are summed anew when affected.
    ``chunks`` (edges a chunk, neighbouring chunks that share what they load) makes the signed messages chunk by chunk.
    ``contextual`` takes and gives sums in their finished form, stripping the old context first. Ends of new edges that
    the graph doesn't have become vertices with zero features; edges of removed vertices go with them.

    The result's graph and states are plans over the old tables and the small tables of changes.
    """
    b = expanded(old, b)
    changes, processed = refresh_from(Frames(old, states, stored is None), b, model, need=need, prune=prune, reorder=reorder, stored=stored, contextual=contextual, chunks=chunks)

    def after() -> list[LayerState]:
        return [LayerState(outside(s.state, c.touched, "vid").unionByName(c.state.select(*s.state.columns)), replaced(s.out, c.out, b.removed)) for s, c in zip(states, changes, strict=True)]

    return Refresh(lambda: apply(old, b), after, [ids(c.front) for c in changes], processed, changes)


def _extremes_lost(aff: DataFrame, q: DataFrame, old: Frames, k: int, layer: Layer, contextual: bool) -> DataFrame:
    """Destinations from which a value as large (or small) as the stored one is taken away: an extreme can't be taken back."""
    op = ">=" if layer.combine_by == "max" else "<="
    minus = aff.where("kind <= 0")
    p = targets(old.out(k - 1, ids(minus, "dst")), layer) if layer.reads_target else None
    stored = old.state(k, ids(minus, "dst"))
    stored = (strip_context(stored, layer) if contextual else stored).withColumnRenamed("vid", "dst")
    rows = messages(minus, q.where("sign < 0"), p, layer).join(beside(stored), ["dst", "rk"])
    return ids(rows.where(" OR ".join(f"c{i} {op} s{i}" for i in range(layer.state_width))), "dst").distinct()


def with_context(state: DataFrame, layer: Layer) -> DataFrame:
    """The state with the context applied to its sums, as a layer's finished aggregate."""
    if layer.strip is None:
        return state
    done = [F.expr(x).alias(f"s{i}") for i, x in enumerate(layer.finish)]
    return state.select("vid", "rk", *done, *[f"s{i}" for i in range(len(done), layer.state_width)], "n")


def strip_context(state: DataFrame, layer: Layer) -> DataFrame:
    """The inverse: sums from a finished aggregate and its context."""
    if layer.strip is None:
        return state
    sums = range(layer.sums)
    rest = [f"s{i}" for i in range(layer.sums, layer.state_width)]
    named = state.select("vid", "rk", *[F.col(f"s{i}").alias(f"a{i}") for i in sums], *rest, "n")
    return named.select("vid", "rk", *[F.expr(x).alias(f"s{i}") for i, x in enumerate(layer.strip)], *rest, "n")
