"""What the incremental refresh is compared with, and the on-demand mode."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.models import Model
from graphrefresh.plans.cut import cut
from graphrefresh.plans.delta import KEY, Refresh, at, ids, outside, refresh, replaced, union
from graphrefresh.plans.full import LayerState, degrees, finish, forward, output, summed, vector
from graphrefresh.sources.graphs import Batch, Graph, apply, expanded, out_of, share


def whole_graph(old: Graph, b: Batch, model: Model) -> Refresh:
    new = apply(old, expanded(old, b))
    states = forward(new, model)
    edges = new.edges.select(*KEY)
    return Refresh(lambda: new, lambda: states, [ids(s.out) for s in states], lambda: [edges for _ in states])


def full_neighbour(old: Graph, b: Batch, model: Model, targets: DataFrame, fanout: int | None = None, seed: str = "s") -> Refresh:
    """Embeddings of ``targets`` over complete (or, with ``fanout``, sampled) neighbourhoods, from the features up, without any stored result."""
    new = apply(old, expanded(old, b))
    need, layers = [targets], []
    for k in range(len(model.layers) - 1, -1, -1):
        edges = out_of(new.edges, need[0], "dst")
        layers.insert(0, cut(edges if fanout is None else sample(edges, fanout, f"{seed}{k}")))
        below, layer = ids(layers[0], "src"), model.layers[k]
        need.insert(0, cut((union(below, need[0]) if layer.self_term or layer.reads_target else below).distinct()))
    h, states, degree = new.vertices, [], None
    if any(x.reads_degree for x in model.layers):
        # messages read the degrees of sources alone, which are what the layers need below them
        h, degree = at(h, need[0]), cut(degrees(out_of(new.edges, union(*need[:-1]), "dst")))
    for layer, edges, wanted in zip(model.layers, layers, need[1:], strict=True):
        state = summed(edges, h, layer, degree)
        # an update that doesn't read the vertex itself needs no embedding of it
        h = cut(output(at(h, wanted) if layer.self_term else ids(at(new.vertices, wanted)), finish(state, layer), layer))
        states.append(LayerState(state, h))
    return Refresh(lambda: new, lambda: states, need[1:], lambda: [e.select(*KEY) for e in layers])


def sample(edges: DataFrame, fanout: int, seed: str, salts: int = 16) -> DataFrame:
    """At most ``fanout`` in-edges of each vertex, uniform and without replacement: those with the least md5.

    The least of each of ``salts`` shares of a vertex's in-edges are found first, so a hub's are never sorted in one task.
    """
    order = [share(seed, F.col("src"), F.col("dst")), "src", "rel"]
    some = edges.withColumn("_s", F.pmod(F.xxhash64("src", "rel"), F.lit(salts)))
    for by in (["dst", "_s"], ["dst"]):
        some = some.withColumn("_n", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("_n") <= fanout).drop("_n")
    return some.drop("_s")


def cache_reuse(old: Graph, states: list[LayerState], b: Batch, model: Model, fronts: list[DataFrame]) -> Refresh:
    """Each affected vertex over all its in-edges; embeddings of unaffected sources come from the stored layer."""
    b = expanded(old, b)
    new = apply(old, b)
    h, out, traces = new.vertices, [], []
    for layer, kept, front in zip(model.layers, states, fronts, strict=True):
        edges = cut(out_of(new.edges, front, "dst"))
        seen, degree = h, None
        if layer.reads_degree:
            ends = cut(union(ids(edges, "src"), *([front] if layer.reads_target else [])).distinct())
            seen, degree = at(h, ends), degrees(out_of(new.edges, ends, "dst"))
        state, base = summed(edges, seen, layer, degree), at(h, front) if layer.self_term else front
        if layer.per_relation:
            state = cut(state)
            part = cut(output(base, finish(state, layer), layer))
        else:
            # sums and embeddings in one table, as the sums are read again
            sums = ["rk", *[f"s{i}" for i in range(layer.state_width)], "n"]
            one = cut(output(base, finish(state, layer, *sums), layer, *sums))
            state, part = one.where("n IS NOT NULL").select("vid", *sums), one.select("vid", *vector(kept.out))
        h = replaced(kept.out, part, b.removed)
        out.append(LayerState(state, h))
        traces.append(edges.select(*KEY))
    return Refresh(lambda: new, lambda: out, fronts, lambda: traces)


def periodic(states: list[LayerState]) -> DataFrame:
    """Embeddings of the last snapshot, as they are."""
    return states[-1].out


def const_message_delta(old: Graph, states: list[LayerState], b: Batch, model: Model) -> tuple[Refresh, bool]:
    """A system for constant messages and plain sums: incremental where the model is of that kind, else over all in-edges. Also says which."""
    done = refresh(old, states, b, model)
    if model.constant_messages:
        return done, True
    return cache_reuse(old, states, b, model, done.changed), False


def on_demand(old: Graph, states: list[LayerState], b: Batch, model: Model, queries: DataFrame) -> tuple[DataFrame, Refresh]:
    """Embeddings of the queried vertices after a batch: at each layer only affected vertices that a query depends on are refreshed.

    What a query depends on is followed down through affected vertices alone; all others are read as they are stored. The
    result is an overlay; the other vertices' states stay as they were and must not be committed.
    """
    b = expanded(old, b)
    fronts = reach(old, b, model)
    need = [cut(at(fronts[-1], queries))]
    for front in reversed([ids(b.changed), *fronts[:-1]]):
        edges = union(out_of(old.edges, need[0], "dst").select(*KEY), out_of(b.inserted, need[0], "dst").select(*KEY))
        need.insert(0, cut(at(front, union(ids(edges, "src"), need[0])).distinct()))
    done = refresh(old, states, b, model, need=need)
    return done.embeddings.join(queries, "vid", "left_semi"), done


def reach(old: Graph, b: Batch, model: Model) -> list[DataFrame]:
    """By layer, the vertices that an expanded batch can affect, from the edges alone: no embedding is computed."""
    moved = union(b.inserted.select(*KEY), b.deleted.select(*KEY))
    ends = cut(ids(moved, "dst").distinct())
    fresh = outside(ids(b.changed), old.vertices, "vid")
    front, fronts = ids(b.changed).distinct(), []
    if not b.changed.isEmpty():
        front, fresh = cut(front), cut(fresh)
    for layer in model.layers:
        touched = union(front, ends) if layer.reads_degree else front
        out = union(out_of(old.edges, touched).select(*KEY), out_of(b.inserted, touched).select(*KEY))
        own = [front] if layer.self_term or layer.reads_target else []
        front = cut(outside(union(ids(out, "dst"), ends, fresh, *own), b.removed, "vid").distinct())
        fronts.append(front)
    return fronts
