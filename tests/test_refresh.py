"""The incremental refresh against whole passes: oracles on the given tables, a hand-made graph, rules switched off."""

import importlib
import random

import pytest

from graphrefresh.models import model
from graphrefresh.oracles import ORACLES
from graphrefresh.plans import baselines, chunk, cost, delta, full
from graphrefresh.plans.full import LayerState, forward
from graphrefresh.queries import QUERIES
from graphrefresh.sources.graphs import Batch, Graph, apply, expanded, features, net
from tests.conftest import SF, rows_of, sql_rows


@pytest.mark.parametrize("name", ["graph_transitions", "full_ggcn", "delta_gcn_features", "delta_gat_vertex_ops", "delta_rgcn_features", "delta_evicted", "ondemand_gcn", "sampled_sage_k5", "chunk_loads", "degree_bands", "chunk_sharing", "activations", "delta_chunked_gin", "scenario_recommendation", "scenario_monitoring", "drift_controlled"])
def test_oracle(spark, sql, name):
    got = QUERIES[name](spark, SF)
    columns, want = sql_rows(sql, ORACLES[name])
    assert sorted(got.columns) == columns
    assert rows_of(got) == want


def make(spark, vids, edges):
    from pyspark.sql import functions as F

    v = spark.createDataFrame([(i,) for i in vids], "vid long").select("vid", *features(F.col("vid")))
    return Graph(v, spark.createDataFrame(edges, "src long, dst long, rel string, w double"))


def batch(spark, ins=(), dele=(), changed=(), removed=()):
    edge = "src long, dst long, rel string, w double"
    return Batch(spark.createDataFrame(list(ins), edge), spark.createDataFrame(list(dele), edge), spark.createDataFrame(list(changed), "vid long, h0 double, h1 double, h2 double, h3 double"), spark.createDataFrame([(x,) for x in removed], "vid long"))


def close(a, b):
    x, y = ({r[0]: r[1:] for r in f.collect()} for f in (a, b))
    return x.keys() == y.keys() and all(abs(p - q) < 1e-9 for k in x for p, q in zip(x[k], y[k], strict=True))


@pytest.mark.parametrize("name", ["agnn", "gat", "gcn", "gin", "pinsage", "rgat", "sage_max"])
def test_random_directed_graph(spark, name):
    """Edges, features, a new and a deleted vertex, an emptied vertex, on a directed graph with sinks."""
    rng = random.Random(name)
    rels = ("contains", "in_order", "placed", "placed_by")
    edges = sorted({(rng.randrange(20), rng.randrange(20)) for _ in range(45)} | {(1, 19)})
    edges = [(a, b, rels[(a + b) % 4], ((a + b) % 4 + 1) / 4) for a, b in edges]
    g = make(spark, range(20), edges)
    gone = 7
    dele = [e for e in edges if gone in e[:2] or e[1] == 3 or e in edges[:2]]
    have = {e[:2] for e in edges}
    ins = [(a, b, "placed", 0.5) for a, b in ((2, 11), (20, 4), (5, 20)) if (a, b) not in have]
    b = batch(spark, ins, dele, [(9, 0.25, 0.5, 0.125, 1.0), (20, 0.5, 0.5, 0.5, 1.0)], [gone])
    m = model(name)
    done = delta.refresh(g, forward(g, m, write=True), b, m)
    assert close(done.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out)


def test_changed_sink_is_summed_anew(spark):
    """Attention reads the destination, so a sink that changed itself is refreshed although no affected edge enters it."""
    g = make(spark, range(4), [(0, 1, "contains", 1.0), (2, 1, "contains", 1.0), (1, 3, "contains", 1.0), (0, 3, "contains", 1.0)])
    b = batch(spark, changed=[(3, 0.9, 0.1, 0.7, 1.0)])
    m = model("gat")
    done = delta.refresh(g, forward(g, m, write=True), b, m)
    assert close(done.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out)
    assert {r[0] for r in done.changed[0].collect()} == {3}


def test_toy_edge_counts(spark):
    """Nine edges, two of them changed: a vertex needs nine edge visits in full and two incrementally."""
    edges = [(5, 1), (6, 1), (5, 3), (2, 3), (5, 4), (1, 2), (3, 2)]
    changed = [(4, 4), (4, 2)]
    edge = lambda es: [(a, b, "contains", 1.0) for a, b in es]
    g = make(spark, range(1, 7), edge(edges))
    b = batch(spark, ins=edge(changed))
    m = model("sage_sum")
    done = delta.refresh(g, forward(g, m, write=True), b, m)
    assert {r[0] for r in done.changed[0].collect()} == {2, 4}
    targets = spark.createDataFrame([(2,)], "vid long")
    fn = baselines.full_neighbour(g, b, m, targets)
    assert [t.count() for t in fn.processed] == [6, 3]
    trace = cost.traces({"delta": done, "full_neighbour": fn})
    assert {r[0] for r in cost.edge_accesses(trace).collect()} == {"delta", "full_neighbour"}
    assert cost.mse(done.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out).first()["mse"] == 0


def test_net_effect_of_updates(spark):
    edges = spark.createDataFrame([(1, 2, "contains", 1.0)], "src long, dst long, rel string, w double")
    ups = spark.createDataFrame([(1, "+", 1, 2, "contains", 1.0), (2, "-", 3, 4, "contains", 1.0), (3, "+", 5, 6, "contains", 0.5), (4, "-", 5, 6, "contains", 0.5), (5, "-", 7, 8, "contains", 1.0), (6, "+", 7, 8, "contains", 0.25), (7, "-", 1, 2, "contains", 1.0)], "seq long, op string, src long, dst long, rel string, w double")
    ins, dele = net(edges, ups)
    assert rows_of(ins) == [("7", "contains", "8", "0.25")] or {tuple(r) for r in ins.collect()} == {(7, 8, "contains", 0.25)}
    assert {tuple(r)[:2] for r in dele.collect()} == {(1, 2)}


def test_on_demand_leaves_other_states(spark):
    g = make(spark, range(5), [(0, 1, "contains", 1.0), (1, 2, "contains", 1.0), (3, 4, "contains", 1.0)])
    b = batch(spark, changed=[(0, 0.9, 0.9, 0.9, 1.0), (3, 0.9, 0.9, 0.9, 1.0)])
    m = model("gin")
    got, run = baselines.on_demand(g, forward(g, m, write=True), b, m, spark.createDataFrame([(2,)], "vid long"))
    want = {r[0]: r[1:] for r in forward(apply(g, expanded(g, b)), m)[-1].out.collect()}
    assert {r[0]: r[1:] for r in got.collect()} == {2: want[2]}
    assert 4 not in {r[0] for r in run.changed[-1].collect()}


def test_plan_has_no_cartesian_product(spark):
    g = make(spark, range(3), [(0, 1, "contains", 1.0)])
    plan = forward(g, model("sage_mean"))[-1].out._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and full.H


def test_chunks_share(spark):
    e = spark.createDataFrame([(s, d) for d in range(8) for s in (1, 2)], "src long, dst long")
    assert tuple(chunk.loads(chunk.plan(e, 4)).first()) == (8, 2)


def test_contract_imports_without_llm(tmp_path):
    """In a copy without the subpackage and its tests, with the pipeline's file and without, all other queries are there."""
    import os
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    copy = shutil.copytree(root, tmp_path / "copy", ignore=shutil.ignore_patterns(".git", "__pycache__", "llm"))
    code = "import __spark_entry__ as e, tests.test_refresh as t; q = e.queries(); assert set(t.QUERIES) == set(q); assert set(e.oracle_sql()) <= set(q)"
    for file in ("", "corpus_pipeline.py"):
        if file:
            os.remove(copy / file)
        subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env={**os.environ, "PYTHONPATH": str(copy)}, timeout=120)


def test_chunks_of_any_size_leave_the_result(spark):
    """A hub over several chunks and destinations larger than a chunk."""
    edges = [(0, d, "contains", 1.0) for d in range(1, 12)] + [(s, 12, "contains", 0.5) for s in range(1, 12)]
    g = make(spark, range(14), edges)
    b = batch(spark, ins=[(12, 13, "contains", 1.0)], dele=edges[:1], changed=[(0, 0.5, 0.25, 0.5, 1.0)])
    for name, chunks in (("gcn", (3, 2)), ("agnn", (1, 1))):
        m = model(name)
        got = delta.refresh(g, forward(g, m, write=True), b, m, chunks=chunks)
        assert close(got.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out)


def test_differences_count_what_is_missing(spark):
    a = spark.createDataFrame([(1, 1.0), (2, 2.0), (3, 0.0)], "vid long, h0 double")
    b = spark.createDataFrame([(1, 1.0), (2, 2.5), (4, 0.0)], "vid long, h0 double")
    assert tuple(cost.difference(a, b).first()) == (0.5, 0.2, 3, 4)


def test_many_rows_are_never_broadcast(spark, monkeypatch):
    """Files of compressed ids look small to Spark; the driver would hold them many times as large."""
    import importlib

    written = importlib.import_module("graphrefresh.plans.cut")
    monkeypatch.setattr(written, "BROADCAST_ROWS", 10)
    edges = [(s, d, "contains", 0.5) for s in range(20) for d in range(20, 40) if (s + d) % 3]
    g = make(spark, range(40), edges)
    b = batch(spark, ins=[(0, 21 + d, "contains", 1.0) for d in range(12) if d % 3 == 0], dele=edges[:30], changed=[(i, 0.5, 0.25, 0.5, 1.0) for i in range(15)])
    b = Batch(written.cut(b.inserted), written.cut(b.deleted), written.cut(b.changed), b.removed)
    for name, chunks in (("sage_max", None), ("sage_min", (8, 2))):
        m = model(name)
        done = delta.refresh(g, forward(g, m, write=True), b, m, chunks=chunks)
        assert close(done.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out)
        small = spark.conf.get("spark.sql.adaptive.enabled")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        try:
            plan = delta.outside(g.edges, delta.ids(written.cut(b.deleted), "dst"))._jdf.queryExecution().executedPlan().toString()
            few = delta.outside(g.edges, delta.ids(written.cut(b.inserted), "dst"))._jdf.queryExecution().executedPlan().toString()
        finally:
            spark.conf.set("spark.sql.adaptive.enabled", small)
        assert "Broadcast" not in plan and "SortMergeJoin" in plan
        assert "BroadcastHashJoin" in few


def test_plans_of_a_refresh_stay_small(spark, monkeypatch):
    """A plan of fifteen joins takes the driver hundreds of MB to plan, however small the tables are."""
    joins = []

    def counted(df, *options, **named):
        joins.append(df._jdf.queryExecution().optimizedPlan().toString().count("Join "))
        return importlib.import_module("graphrefresh.plans.cut").cut(df, *options, **named)

    monkeypatch.setattr(delta, "cut", counted)
    edges = [(s, d, "contains", 0.5) for s in range(20) for d in range(20, 40) if (s + d) % 3]
    g = make(spark, range(40), edges)
    b = batch(spark, ins=[(0, 21, "contains", 1.0)], dele=edges[:30], changed=[(i, 0.5, 0.25, 0.5, 1.0) for i in range(15)])
    kept = g.vertices.where("vid % 2 = 0").select("vid")
    m = model("sage_max")
    states = [LayerState(s.state.join(kept, "vid", "left_semi"), s.out) for s in forward(g, m, write=True)]
    done = delta.refresh(g, states, b, m, stored=[kept] * 2)
    assert close(done.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out)
    assert max(joins) <= 12, joins


def test_garbage_of_plans_is_collected(spark, monkeypatch):
    """Between two written tables, once the driver's heap has grown; never where tasks share the heap."""
    written = importlib.import_module("graphrefresh.plans.cut")
    jvm = spark.sparkContext._jvm
    heap = jvm.java.lang.Runtime.getRuntime()
    monkeypatch.setattr(written, "_KEPT", {})
    jvm.java.lang.System.gc()
    jvm.java.nio.ByteBuffer.allocate(150 * 2**20).capacity()
    full = written._used(heap)
    written.cut(spark.range(3))
    assert not written._KEPT
    monkeypatch.setattr(written, "_alone", lambda sc: False)
    monkeypatch.setattr(written, "GARBAGE_MB", 0)
    assert written.cut(spark.range(3)).count() == 3
    assert 0 < written._KEPT[spark.sparkContext.applicationId] < full


def test_first_front_is_looked_up_once(spark, monkeypatch):
    """The changed vertices' old embeddings are read up to nine times in the first layer; their joins are planned once."""
    joins = []

    def counted(df, *options, **named):
        joins.append(df._jdf.queryExecution().optimizedPlan().toString().count("Join "))
        return importlib.import_module("graphrefresh.plans.cut").cut(df, *options, **named)

    monkeypatch.setattr(delta, "cut", counted)
    edges = [(s, d, "contains", 0.5) for s in range(20) for d in range(20, 40) if (s + d) % 3]
    g = make(spark, range(40), edges)
    b = batch(spark, ins=[(0, 21, "contains", 1.0), (0, 50, "contains", 1.0)], dele=edges[:30], changed=[(i, 0.5, 0.25, 0.5, 1.0) for i in range(15)])
    kept = g.vertices.where("vid % 2 = 0").select("vid")
    m = model("sage_min")
    states = [LayerState(s.state.join(kept, "vid", "left_semi"), s.out) for s in forward(g, m, write=True)]
    done = delta.refresh(g, states, b, m, stored=[kept] * 2)
    assert close(done.embeddings, forward(apply(g, expanded(g, b)), m)[-1].out)
    assert max(joins) <= 8, joins


def test_freed_native_memory_goes_back(spark, monkeypatch):
    """Together with the heap's garbage, and never where tasks share the heap."""
    written = importlib.import_module("graphrefresh.plans.cut")
    said = []
    monkeypatch.setattr(written, "_KEPT", {})
    monkeypatch.setattr(written, "trim", lambda sc, trim=written.trim: said.append(trim(sc)))
    written.cut(spark.range(3))
    assert not said
    monkeypatch.setattr(written, "_alone", lambda sc: False)
    monkeypatch.setattr(written, "GARBAGE_MB", -(10**6))
    assert written.cut(spark.range(3)).count() == 3
    assert len(said) == 2 and all("native heap" in x for x in said)
