"""One query for each method, variant, baseline, measure and graph."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh import dense, relational, workloads
from graphrefresh.functions import weights
from graphrefresh.models import ZOO, model
from graphrefresh.plans import baselines, chunk, cost, upkeep
from graphrefresh.plans.cut import cut, work_dir
from graphrefresh.plans.delta import at, ids, refresh, with_context
from graphrefresh.plans.full import LayerState, forward, rebuilt, vector
from graphrefresh.sources import files, graphs
from graphrefresh.sources.graphs import Batch, Graph

#: Models whose messages read both ends run on the directed graph, typed ones on the typed one.
GRAPH_OF = {m: "transitions" for m in ("gat", "agnn", "ggcn", "monet", "pinsage", "gcn")} | {m: "typed" for m in ("rgcn", "rgat", "rgcn_relation")}
EDGES = {"inserts": 0.05, "deletes": 0.01}
FEATURES = {"inserts": 0.05, "deletes": 0.01, "changes": 0.02}
VERTICES = {"inserts": 0.05, "deletes": 0.01, "changes": 0.01, "removals": 0.01}


GRAIN = 10_007
#: Edges with ends that no graph has.
NEW_ENDS = [(0, -4, "contains", 0.5), (-4, 1, "contains", 0.25), (-8, -4, "contains", 1.0)]


def graph_of(name: str) -> str:
    return GRAPH_OF.get(name, "order_part")


def shown(h: DataFrame) -> DataFrame:
    """Rounded to a multiple of 1/GRAIN, a prime, so that sums and means of binary fractions are never half-way."""
    return h.select("vid", *[(F.round(F.col(c) * float(GRAIN), 0) / float(GRAIN) + F.lit(0.0)).alias(f"d{i}") for i, c in enumerate(vector(h))])


def prepared(spark: SparkSession, sf_dir: str, graph: str, shares: dict) -> tuple[Graph, Batch]:
    g, stream = graphs.snapshot(spark, sf_dir, graph)
    g = Graph(cut(g.vertices, probed=True), g.edges)
    b = graphs.batch(g, stream, **shares)
    none = {n for n, s in (("changed", "changes"), ("removed", "removals")) if not shares.get(s)}
    return g, Batch(*[df.limit(0) if n in none else cut(df) for n, df in (("inserted", b.inserted), ("deleted", b.deleted), ("changed", b.changed), ("removed", b.removed))])


def full(spark: SparkSession, sf_dir: str, name: str, reorder: bool = True) -> DataFrame:
    g, _ = graphs.snapshot(spark, sf_dir, graph_of(name))
    return shown(forward(g, model(name), reorder)[-1].out)


def delta(spark: SparkSession, sf_dir: str, name: str, shares: dict, depth: int = 2, **options) -> DataFrame:
    g, b = prepared(spark, sf_dir, graph_of(name), shares)
    m = model(name, depth)
    return shown(refresh(g, forward(g, m, write=True), b, m, **options).embeddings)


def delta_contextual(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    g, b = prepared(spark, sf_dir, graph_of(name), FEATURES)
    m = model(name)
    states = [LayerState(with_context(s.state, x), s.out) for s, x in zip(forward(g, m, write=True), m.layers, strict=True)]
    return shown(refresh(g, states, b, m, contextual=True).embeddings)


def delta_evicted(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Sums are kept for half of the vertices only."""
    g, b = prepared(spark, sf_dir, graph_of(name), FEATURES)
    m = model(name)
    kept = cut(ids(g.vertices).where(graphs.share("k", F.col("vid")) < 0.5))
    states = [LayerState(cut(at(s.state, kept), probed=True), s.out) for s in forward(g, m, write=True)]
    return shown(refresh(g, states, b, m, stored=[kept] * len(states)).embeddings)


def delta_new_vertices(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """New edges bring ends that the graph doesn't have: they become vertices with zero features."""
    g, b = prepared(spark, sf_dir, "transitions", EDGES)
    m = model(name)
    extra = spark.createDataFrame(NEW_ENDS, g.edges.schema)
    return shown(refresh(g, forward(g, m, write=True), Batch(cut(b.inserted.unionByName(extra)), b.deleted, b.changed, b.removed), m).embeddings)


def delta_layout(spark: SparkSession, sf_dir: str, layout: str) -> DataFrame:
    """States that keep sums alone, embeddings made anew from them; or states of the half of the vertices with most in-edges."""
    g, b = prepared(spark, sf_dir, "order_part", FEATURES)
    m = model("sage_mean")
    states = forward(g, m, write=True)
    if layout == "sums":
        return shown(refresh(g, rebuilt(g.vertices, states, m), b, m).embeddings)
    states, kept = upkeep.evict(g, states, 0.5)
    return shown(refresh(g, states, b, m, stored=[cut(kept[0])] * len(states)).embeddings)


def wide(spark: SparkSession, sf_dir: str, kind: str, shares: dict | None = None) -> DataFrame:
    """Layers of width 64 over the vectors of ``embeddings``, on the graph of nearest vectors; the model is written and loaded again."""
    g, stream = graphs.snapshot(spark, sf_dir, "knn")
    width = graphs.table(spark, sf_dir, "embeddings").agg(F.max(F.size("embedding"))).first()[0] or 1
    x = graphs.table(spark, sf_dir, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("vid"), *[(F.round(F.col("embedding")[i].cast("double") * 64) / 64).alias(f"h{i}") for i in range(width)])
    g = Graph(cut(x), g.edges)
    path = f"{work_dir(spark)}/model-{kind}"
    files.save_model(spark, dense.dense_model(kind, dense.drawn_weights([width, 64, 64])), path)
    m = files.load_model(spark, path)
    if shares is None:
        return shown(forward(g, m)[-1].out)
    b = graphs.batch(g, stream, **shares)
    b = Batch(cut(b.inserted), cut(b.deleted), cut(b.changed), b.removed)
    return shown(refresh(g, forward(g, m, write=True), b, m).embeddings)


def drift_controlled(spark: SparkSession, sf_dir: str, off: float = 0.125) -> DataFrame:
    """States of which a tenth of the vertices have drifted: the audit finds it and a complete pass puts it right."""
    g, _ = graphs.snapshot(spark, sf_dir, "transitions")
    g, m = Graph(cut(g.vertices), g.edges), model("gcn")
    far = F.when(graphs.share("drift", F.col("vid")) < 0.1, off).otherwise(0.0)
    drifted = [LayerState(s.state, s.out.select("vid", *[(F.col(c) + far).alias(c) for c in vector(s.out)])) for s in forward(g, m, write=True)]
    return shown(upkeep.corrected(g, drifted, m, 1e-6, 0.5)[0][-1].out)


def recommendation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Live interactions of users with items: after the newest, the embeddings of the users who made them, refreshed on demand."""
    g, b = prepared(spark, sf_dir, "user_item", EDGES)
    m = model("sage_mean")
    active = cut(ids(b.inserted, "src").where("vid % 2 = 0").distinct())
    return shown(baselines.on_demand(g, forward(g, m, write=True), b, m, active)[0])


def monitoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Latest transactions on typed relations: ``vid, moved`` of the vertices whose embedding they move, and how far (sum of absolute changes)."""
    g, b = prepared(spark, sf_dir, "typed", EDGES)
    m = model("rgcn")
    front = refresh(g, forward(g, m, write=True), b, m).changes[-1].front
    far = sum((F.abs(F.col(c) - F.coalesce(F.col(f"o{c[1:]}"), F.lit(0.0))) for c in front.columns if c[0] == "h"), F.lit(0.0))
    return front.select("vid", (F.round(far * float(GRAIN), 0) / float(GRAIN)).alias("moved")).where("moved > 0")


def activations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The activation functions on a component of every vector."""
    x = graphs.table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.get("embedding", F.lit(0)).cast("double").alias("x"))
    return x.select("vec_id", *[F.round(F.expr(f("x")), 6).alias(f.__name__) for f in ACTIVATIONS])


ACTIVATIONS = (weights.relu, weights.leaky_relu, weights.elu, weights.sigmoid, weights.tanh)


def delta_two_epochs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Insertions first, then everything else of the same batch."""
    g, b = prepared(spark, sf_dir, graph_of(name), FEATURES)
    m = model(name)
    one = refresh(g, forward(g, m, write=True), Batch(b.inserted, b.deleted.limit(0), b.changed.limit(0), b.removed), m)
    return shown(refresh(one.graph, one.states, Batch(b.inserted.limit(0), b.deleted, b.changed, b.removed), m).embeddings)


def _compared(spark: SparkSession, sf_dir: str, name: str, method: str, fanout: int | None = None) -> DataFrame:
    g, b = prepared(spark, sf_dir, graph_of(name), FEATURES)
    m = model(name)
    states = forward(g, m, write=True)
    if method == "whole":
        return shown(baselines.whole_graph(g, b, m).embeddings)
    if method == "periodic":
        return shown(baselines.periodic(states))
    if method == "const":
        return shown(baselines.const_message_delta(g, states, b, m)[0].embeddings)
    done = refresh(g, states, b, m)
    if method == "reuse":
        return shown(baselines.cache_reuse(g, states, b, m, done.changed).embeddings)
    if method == "demand":
        queries = cut(done.changed[-1].where(graphs.share("q", F.col("vid")) < 0.2))
        return shown(baselines.on_demand(g, states, b, m, queries)[0])
    return shown(baselines.full_neighbour(g, b, m, done.changed[-1], fanout).embeddings)


def _runs(spark: SparkSession, sf_dir: str, name: str, graph: str) -> dict:
    g, b = prepared(spark, sf_dir, graph, {"inserts": 0.002, "deletes": 0.0002})
    m = model(name)
    states = forward(g, m, write=True)
    done = refresh(g, states, b, m)
    return {"delta": done, "cache_reuse": baselines.cache_reuse(g, states, b, m, done.changed), "full_neighbour": baselines.full_neighbour(g, b, m, done.changed[-1]), "sampled_5": baselines.full_neighbour(g, b, m, done.changed[-1], 5), "sampled_10": baselines.full_neighbour(g, b, m, done.changed[-1], 10), "whole_graph": baselines.whole_graph(g, b, m)}


def measured(spark: SparkSession, sf_dir: str, measure: str, name: str = "sage_mean", graph: str = "order_part") -> DataFrame:
    runs = _runs(spark, sf_dir, name, graph)
    trace = cut(cost.traces(runs))
    if measure == "bands":
        return cost.by_degree_band(trace, runs["delta"].graph.edges, "delta", "full_neighbour")
    if measure == "affected":
        return cost.affected_share(runs["delta"])
    if measure == "difference":
        return cost.difference(runs["delta"].embeddings, runs["whole_graph"].embeddings).select((F.round("max_abs", 9) + F.lit(0.0)).alias("max_abs"), (F.round("max_relative", 6) + F.lit(0.0)).alias("max_relative"), "mismatches", "vertices")
    if measure == "mse":
        return cost.mse(runs["delta"].embeddings, runs["whole_graph"].embeddings)
    return {"edges": cost.edge_accesses, "vertices": cost.vertex_accesses, "ratio": cost.normalised, "redundant": cost.redundant_share}[measure](trace)


def state_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, _ = graphs.snapshot(spark, sf_dir, "order_part")
    return cost.state_bytes(g.vertices, forward(g, model("sage_mean"), write=True))


def accuracies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of vertices whose label each approach gets right; labels are those of the whole new graph, one in twenty flipped."""
    g, b = prepared(spark, sf_dir, "transitions", {"inserts": 0.5, "deletes": 0.05, "changes": 0.2})
    m = model("sage_mean")
    states = forward(g, m, write=True)
    done = refresh(g, states, b, m)
    truth = cost.label(baselines.whole_graph(g, b, m).embeddings).withColumn("y", F.when(graphs.share("flip", F.col("vid")) < 0.05, F.pmod(F.col("y") + 1, F.lit(4))).otherwise(F.col("y")))
    truth = cut(truth)
    ways = {"delta": done.embeddings, "periodic": baselines.periodic(states)} | {f"sampled_{k}": baselines.full_neighbour(g, b, m, ids(g.vertices), k).embeddings for k in (5, 10, 20)}
    rows = [cost.accuracy(h, truth).select(F.lit(n).alias("approach"), "accuracy") for n, h in ways.items()]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def edges_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return graphs.with_weights(graphs.EDGES[name](spark, sf_dir)).select("src", "dst", "rel", "w", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))


def chunk_loads(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chunk.loads(chunk.plan(graphs.EDGES["order_part"](spark, sf_dir).select("src", "dst"), 8192))


def chunk_sharing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chunk.sharing(chunk.plan(graphs.EDGES["order_part"](spark, sf_dir).select("src", "dst"), 8192))


def degree_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.degree_bands(graphs.EDGES["order_part"](spark, sf_dir)).groupBy("band").agg(F.count(F.lit(1)).alias("vertices"), F.sum("deg").alias("in_edges"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f"graph_{n}": partial(edges_of, name=n) for n in graphs.EDGES}
for _n in ZOO:
    QUERIES[f"full_{_n}"] = partial(full, name=_n)
    QUERIES[f"delta_{_n}_edges"] = partial(delta, name=_n, shares=EDGES)
    QUERIES[f"delta_{_n}_features"] = partial(delta, name=_n, shares=FEATURES)
for _n in ("gin", "gcn", "gat", "rgcn"):
    QUERIES[f"delta_{_n}_vertex_ops"] = partial(delta, name=_n, shares=VERTICES)
QUERIES |= {
    "full_unordered_gcn": partial(full, name="gcn", reorder=False), "full_unordered_gat": partial(full, name="gat", reorder=False),
    "delta_depth3_gin": partial(delta, name="gin", shares=FEATURES, depth=3), "delta_depth3_gat": partial(delta, name="gat", shares=FEATURES, depth=3),
    "delta_pruned": partial(delta, name="gin", shares=FEATURES, prune=True), "delta_no_reorder": partial(delta, name="gcn", shares=FEATURES, reorder=False),
    "delta_contextual_gcn": partial(delta_contextual, name="gcn"), "delta_contextual_gat": partial(delta_contextual, name="gat"),
    "delta_evicted": partial(delta_evicted, name="sage_mean"), "delta_two_epochs_gin": partial(delta_two_epochs, name="gin"), "delta_two_epochs_gat": partial(delta_two_epochs, name="gat"),
    "delta_evicted_sage_max": partial(delta_evicted, name="sage_max"), "delta_evicted_sage_min": partial(delta_evicted, name="sage_min"), "delta_evicted_gin": partial(delta_evicted, name="gin"), "delta_evicted_gat": partial(delta_evicted, name="gat"),
    "delta_new_vertices": partial(delta_new_vertices, name="gcn"), "delta_new_vertices_gat": partial(delta_new_vertices, name="gat"),
    "delta_agg_only_layout": partial(delta_layout, layout="sums"), "delta_evicted_by_degree": partial(delta_layout, layout="degree"),
    "whole_graph": partial(_compared, name="sage_mean", method="whole"), "periodic": partial(_compared, name="sage_mean", method="periodic"), "constmsg_fallback": partial(_compared, name="gat", method="const"),
    "cachereuse_gcn": partial(_compared, name="gcn", method="reuse"), "cachereuse_gat": partial(_compared, name="gat", method="reuse"), "fullnbr_sage_mean": partial(_compared, name="sage_mean", method="full"), "fullnbr_gat": partial(_compared, name="gat", method="full"),
    "sampled_sage_k5": partial(_compared, name="sage_mean", method="full", fanout=5), "sampled_sage_k10": partial(_compared, name="sage_mean", method="full", fanout=10), "sampled_sage_k20": partial(_compared, name="sage_mean", method="full", fanout=20),
    "ondemand_gcn": partial(_compared, name="gcn", method="demand"), "ondemand_gat": partial(_compared, name="gat", method="demand"),
    "edge_accesses": partial(measured, measure="edges"), "vertex_accesses": partial(measured, measure="vertices"), "normalised_volume": partial(measured, measure="ratio"), "redundant_share": partial(measured, measure="redundant"),
    "affected_share": partial(measured, measure="affected"), "volume_by_degree_band": partial(measured, measure="bands", graph="cust_part"), "embedding_difference": partial(measured, measure="difference"), "mse_delta_vs_full": partial(measured, measure="mse"),
    "state_bytes_by_layout": state_bytes, "accuracy_by_approach": accuracies, "chunk_loads": chunk_loads, "chunk_sharing": chunk_sharing, "activations": activations, "drift_controlled": drift_controlled, "scenario_recommendation": recommendation, "scenario_monitoring": monitoring, "degree_bands": degree_bands,
}
#: Edges a chunk, and chunks that share what they load.
CHUNKED = {"gcn": (512, 1), "gin": (512, 4), "gat": (2048, 2), "sage_max": (512, 4)}
for _n, _c in CHUNKED.items():
    QUERIES[f"delta_chunked_{_n}"] = partial(delta, name=_n, shares=FEATURES, chunks=_c)
for _n in ("sage_sum", "sage_mean", "gin", "gcn"):
    QUERIES[f"constmsg_{_n}"] = partial(_compared, name=_n, method="const")
for _n in dense.KINDS:
    QUERIES[f"full_wide_{_n}"] = partial(wide, kind=_n)
    QUERIES[f"delta_wide_{_n}"] = partial(wide, kind=_n, shares=FEATURES)
QUERIES |= relational.QUERIES | workloads.QUERIES
