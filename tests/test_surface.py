"""Relational operations against SQL; model checks, two-hop upkeep and files on small graphs."""

import pytest
from pyspark.sql import functions as F

from graphrefresh.models import ZOO, model
from graphrefresh.operators import joins, windows
from graphrefresh.plans import catalogue, twohop, verify
from graphrefresh.relational import ORACLES, QUERIES
from graphrefresh.sources import files
from tests.conftest import SF, rows_of, sql_rows


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sql, name):
    got = QUERIES[name](spark, SF)
    columns, want = sql_rows(sql, ORACLES[name])
    assert sorted(got.columns) == columns
    assert rows_of(got) == want


def test_as_of_takes_nulls_ties_and_far_stretches(spark):
    left = spark.createDataFrame([(1, 5), (1, 5000), (2, 9), (None, 7)], "k long, t long")
    right = spark.createDataFrame([(1, 5, 1.0), (1, 4, 2.0), (2, 50, 3.0)], "k long, t long, v double")
    got = {(r.k, r.t): r.v for r in joins.as_of(left, right, "k", "t", "v", 10).collect()}
    assert got == {(1, 5): 2.0, (1, 5000): 1.0, (2, 9): None, (None, 7): None}


def test_nearest_in_blocks_is_the_same(spark):
    rows = spark.range(40).select(F.col("id").alias("vec_id"), F.array(*[(F.pmod(F.xxhash64("id", F.lit(i)), F.lit(7)) - 3).cast("double") for i in range(5)]).alias("embedding"))
    assert rows_of(joins.nearest(rows, 3)) == rows_of(joins.nearest(rows, 3, block_rows=7))


def test_ranks_are_a_whole_order(spark):
    rows = spark.range(100).select(F.pmod(F.col("id") * 37, F.lit(101)).alias("x"))
    got = [r["rank"] for r in windows.ranked(rows, F.floor(F.col("x") / 9), "x").orderBy("x").collect()]
    assert got == list(range(100))


@pytest.mark.parametrize(("name", "fails"), [("gcn", set()), ("gat", {"source_only"}), ("sage_max", {"sum_mergeable"})])
def test_conditions(spark, name, fails):
    got = {r.condition for r in verify.conditions(spark, ZOO[name](1)).collect() if not r.holds}
    assert got == fails


def test_context_that_cannot_be_undone_is_found(spark):
    got = {r.condition for r in verify.conditions(spark, verify.without_strip(ZOO["sage_mean"](1))).collect() if not r.holds}
    assert got == {"combine_invertible"}


def test_catalogue_matches_the_zoo():
    h, update = [f"h{i}" for i in range(4)], ZOO["sage_mean"](1).update
    made, known = catalogue.decompose("mean", h, update), ZOO["sage_mean"](1)
    assert (made.finish, made.strip, made.state_width) == (known.finish, known.strip, known.state_width)
    assert catalogue.known("Graph-SAGE").name == "sage_mean" and catalogue.known("nothing") is None


def test_two_hop_under_changes(spark):
    edge = "src long, dst long"
    old = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (2, 4)], edge)
    ins, dele = spark.createDataFrame([(4, 1), (3, 3)], edge), spark.createDataFrame([(2, 3)], edge)
    new = spark.createDataFrame([(1, 2), (3, 1), (2, 4), (4, 1), (3, 3)], edge)
    assert rows_of(twohop.two_hop_delta(old, twohop.two_hop(old), ins, dele)) == rows_of(twohop.two_hop(new))


def test_adjacency_runs_and_compaction(spark, tmp_path):
    edge = "src long, dst long, rel string, w double"
    make = lambda rows: spark.createDataFrame(rows, edge)
    a = files.Adjacency(spark, str(tmp_path), buckets=4)
    a.create(make([(1, 2, "contains", 1.0), (2, 3, "contains", 1.0)]))
    a.append(make([(5, 6, "contains", 0.5)]), make([(1, 2, "contains", 1.0)]), 0, 1)
    want = {(2, 3, "contains", 1.0), (5, 6, "contains", 0.5)}
    assert {tuple(r) for r in a.edges(0, 1, "dst").collect()} == want
    assert {tuple(r) for r in a.edges(a.compact(0, 1), 0).collect()} == want
    five = a.bucket_of(spark.createDataFrame([(5,)], "vid long"))
    assert (5, 6, "contains", 0.5) in {tuple(r) for r in a.edges(0, 1, of=five).collect()}


def test_edge_files_and_models_come_back(spark, tmp_path):
    e = spark.createDataFrame([(1, 2, "contains", 0.25)], files.EDGE)
    for kind in ("csv", "json"):
        files.write_edges(e, f"{tmp_path}/{kind}", kind)
        assert rows_of(files.read_edges(spark, f"{tmp_path}/{kind}", kind)) == rows_of(e)
    files.save_model(spark, model("gat"), f"{tmp_path}/model")
    assert files.load_model(spark, f"{tmp_path}/model") == model("gat")


def test_conditions_are_tried_on_the_given_vectors(spark, sql):
    from graphrefresh import workloads
    from graphrefresh.oracles import ORACLES as ALL

    got = workloads.conditions_report(spark, SF)
    assert all("embeddings" in f for f in got.inputFiles()) and got.inputFiles()
    columns, want = sql_rows(sql, ALL["conditions_report"])
    assert sorted(got.columns) == columns
    # numbers without a fraction, and nulls, are not written alike by the two
    same = lambda rows: sorted(tuple({"nan": "None", "<NA>": "None"}.get(c, c) for c in r) for r in rows)
    assert same(rows_of(got)) == same(want)
    few = spark.createDataFrame([(1, [1.0]), (2, None), (3, [0.5, None, 0.25])], "vec_id long, embedding array<float>")
    assert {r.condition for r in verify.conditions(spark, ZOO["sage_max"](1), vectors=few).collect() if not r.holds} == {"sum_mergeable"}


def test_no_query_lists_the_code_alone():
    """A list of the models' own settings comes from no table, so it is no query."""
    from graphrefresh import workloads

    assert "model_catalogue" not in workloads.QUERIES


def test_models_of_one_graph_share_it_and_its_batches(spark, monkeypatch):
    from graphrefresh import workloads

    made = []
    ready, settled = workloads._ready, workloads.cut
    monkeypatch.setattr(workloads, "_ready", lambda *a: made.append("graph") or ready(*a))
    monkeypatch.setattr(workloads, "cut", lambda df, **kw: made.append("table") or settled(df, **kw))
    monkeypatch.setattr(workloads, "_settled", lambda g, m: [])
    monkeypatch.setattr(workloads.cost, "timed", lambda run: 1.0)
    rows = workloads.response_times(spark, SF, models=("gcn", "gat"), runs=1).collect()
    assert [(r.model, r.method, r.seconds) for r in rows][::5] == [("gcn", "delta", 1.0), ("gat", "delta", 1.0)] and len(rows) == 10
    # the vertices, and two tables for each of two batches
    assert made.count("graph") == 1 and made.count("table") == 5


def test_timed_refreshes_expand_a_batch_once(spark, monkeypatch):
    from graphrefresh import workloads
    from graphrefresh.sources import graphs

    methods, _ = workloads.prepared_runs(spark, SF, "transitions", "gcn", 5)
    todo, made, settled = methods("once"), [], graphs.cut
    monkeypatch.setattr(graphs, "cut", lambda df, **kw: made.append(1) or settled(df, **kw))
    got = {}
    for method in ("delta", "cache_reuse", "full_neighbour", "sampled_5"):
        made.clear()
        got[method] = todo[method]().collect()
        assert len(made) == 1, method
    # the sums that are read from the table of the last layer give the embeddings that the other methods give
    rounded = lambda rows: {r.vid: tuple(round(r[f"h{i}"], 6) for i in range(4)) for r in rows}
    want = rounded(todo["whole_graph"]().collect())
    full, delta = rounded(got["full_neighbour"]), rounded(got["delta"])
    assert full and full.items() <= want.items() and delta.items() <= want.items()
    assert {r.vid for r in got["cache_reuse"]} <= full.keys() and all(r.n > 0 and r.s4 == r.n for r in got["cache_reuse"])
