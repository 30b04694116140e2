import datetime

import pytest
from pyspark.sql import functions as F

from graphrefresh.models import model
from graphrefresh.plans.delta import refresh_from
from graphrefresh.plans.full import forward
from graphrefresh.sources.graphs import Batch, Graph, expanded
from graphrefresh.sources.store import Store, StoredFrames
from graphrefresh.streaming.refresh import UPDATE, Refresher, update_rates, updates
from graphrefresh.streaming.sums import followed, layer_one_sums, whole_sums
from tests.test_refresh import batch, close, make

AT = datetime.datetime(2024, 1, 1)


def test_epochs_equal_one_pass(spark, tmp_path):
    """Edges, a repeated update, features (late ones lose), a new vertex by an edge alone, a deleted vertex; compaction in between."""
    edges = [(a, (a * 3 + 1) % 8, "contains", 1.0) for a in range(8)]
    g = make(spark, range(8), edges)
    later = AT + datetime.timedelta(minutes=1)
    files = [
        [(1, "+", 0, 5, "contains", 0.5, AT, None), (1, "+", 0, 5, "contains", 0.5, AT, None), (2, "set", 3, None, None, None, later, [0.5, 0.25, 0.5, 1.0])],
        [(3, "-", 0, 1, "contains", 1.0, AT, None), (4, "+", 7, 2, "contains", 0.25, AT, None), (5, "+", 9, 2, "contains", 0.25, AT, None)],
        [(6, "drop", 6, None, None, None, later, None), (7, "set", 4, None, None, None, later, [0.25, 0.25, 0.25, 1.0]), (8, "set", 4, None, None, None, AT, [9.0, 9.0, 9.0, 9.0])],
    ]
    for ups in files:
        spark.createDataFrame(ups, UPDATE).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    m = model("gcn")
    r = Refresher(g, m, str(tmp_path / "state"), rows_per_bucket=2, max_runs=2)
    r.run(updates(spark, str(tmp_path / "in")), str(tmp_path / "check"))
    last = max(int(n[4:]) for n in r.store.by_src._names(r.store.by_src.path) if n.startswith("run="))
    want = [e for e in edges if e[:2] != (0, 1) and 6 not in e[:2]] + [(0, 5, "contains", 0.5), (7, 2, "contains", 0.25), (9, 2, "contains", 0.25)]
    features = {x[0]: x[1:] for x in g.vertices.collect()} | {3: (0.5, 0.25, 0.5, 1.0), 4: (0.25, 0.25, 0.25, 1.0), 9: (0.0, 0.0, 0.0, 0.0)}
    del features[6]
    new = Graph(spark.createDataFrame([(k, *v) for k, v in features.items()], g.vertices.schema), spark.createDataFrame(want, g.edges.schema))
    assert close(r.embeddings(last), forward(new, m)[-1].out)
    rates = update_rates(spark.read.schema(UPDATE).parquet(str(tmp_path / "in")), "1 hour")
    assert {x.op: x.updates for x in rates.collect()} == {"+": 4, "-": 1, "set": 3, "drop": 1}


def test_reads_follow_the_batch(spark, tmp_path):
    """The same one-edge batch reads as many buckets in a graph of rings that is eight times as large."""
    read = []
    for rings in (40, 320):
        v = spark.range(5 * rings).withColumnRenamed("id", "vid").select("vid", *[(F.col("vid") % 7 / 8.0).alias(f"h{i}") for i in range(4)])
        e = v.select(F.col("vid").alias("src"), (F.floor(F.col("vid") / 5) * 5 + (F.col("vid") + 1) % 5).alias("dst"), F.lit("contains").alias("rel"), F.lit(1.0).alias("w"))
        m = model("gin")
        store = Store.create(Graph(v, e), m, str(tmp_path / str(rings)), rows_per_bucket=5)
        before = StoredFrames(store, -1)
        b = expanded(None, batch(spark, [(0, 2, "contains", 0.5)]), before)
        changes, _ = refresh_from(before, b, m)
        store.commit(b, changes, 0)
        read.append((len(store.by_src._present[-1]), sum(t.buckets_read for t in store.tables)))
        if rings == 40:
            assert close(store.outs[-1].at(0), forward(store.graph(0), m)[-1].out)
    (few, small), (many, large) = read
    assert many > 4 * few and large <= small + 6 and large < many


def test_empty_micro_batch(spark, tmp_path):
    m = model("sage_mean")
    g = make(spark, range(3), [(0, 1, "contains", 1.0)])
    r = Refresher(g, m, str(tmp_path))
    r.on_batch(spark.createDataFrame([], UPDATE), 0)
    assert close(r.embeddings(0), forward(g, m)[-1].out) and isinstance(batch(spark), Batch)


def test_exact_passes_end_drift(spark, tmp_path):
    """A state that was put out of order is right again after the pass that follows the second batch."""
    g, m = make(spark, range(4), [(0, 1, "contains", 1.0), (1, 2, "contains", 1.0)]), model("gin")
    r = Refresher(g, m, str(tmp_path), exact_every=2)
    wrong = r.store.outs[-1].at(-1).withColumn("h0", F.col("h0") + 1).cache()
    wrong.count()
    r.store.outs[-1].write_base(wrong, -1)
    for epoch, ups in enumerate(([(1, "+", 2, 3, "contains", 1.0, AT, None)], [(2, "-", 0, 1, "contains", 1.0, AT, None)])):
        r.on_batch(spark.createDataFrame(ups, UPDATE), epoch)
        want = forward(r.store.graph(epoch), m)[-1].out
        assert close(r.embeddings(epoch), want) == (epoch == 1)


def test_running_sums_of_a_stream(spark, tmp_path):
    """New and deleted edges over three micro-batches, a hub in several parts, a vertex that loses all its edges."""
    m = model("sage_sum")
    edges = [[(a, 9, "contains", 1.0, 1) for a in range(8)] + [(1, 5, "contains", 1.0, 1)], [(1, 9, "contains", 1.0, -1), (1, 5, "contains", 1.0, -1)], [(9, 2, "contains", 1.0, None), (77, 2, "contains", 1.0, 1)]]
    g = make(spark, range(10), [(a, 9, "contains", 1.0) for a in range(8) if a != 1] + [(9, 2, "contains", 1.0)])
    schema = "src long, dst long, rel string, w double, sign int"
    for rows in edges:
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    keep = lambda df, epoch: df.withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(str(tmp_path / f"out/run={epoch}"))
    layer_one_sums(stream, g.vertices, m.layers[0], 4).writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    parts = spark.read.parquet(str(tmp_path / "out")).drop("run")
    assert parts.where("vid = 9").select("salt").distinct().count() > 1
    got = whole_sums(parts, "epoch")
    assert close(got, forward(g, m)[0].state.select(*got.columns))
    with pytest.raises(ValueError):
        layer_one_sums(stream, g.vertices, model("gat").layers[0])


def test_events_that_follow(spark, tmp_path):
    """One click inside the hour, one too late, one for nobody; a repeated impression; an empty stream."""
    at = lambda minutes: AT + datetime.timedelta(minutes=minutes)
    rows = {"seen": [(1, at(0)), (2, at(1)), (2, at(1)), (3, at(2)), (None, at(0))], "click": [(1, at(30)), (2, at(60)), (3, at(90)), (4, at(3)), (None, at(5))], "none": []}
    streams = {}
    for name, xs in rows.items():
        spark.createDataFrame(xs, "user long, ts timestamp").coalesce(1).write.parquet(str(tmp_path / name))
        streams[name] = spark.readStream.schema("user long, ts timestamp").parquet(str(tmp_path / name))
    found = {}
    for other in ("click", "none"):
        q = followed(streams["seen"], streams[other], "user").writeStream.format("memory").queryName(f"followed_{other}").option("checkpointLocation", str(tmp_path / f"c_{other}")).trigger(availableNow=True).start()
        q.awaitTermination()
        found[other] = sorted(r.user for r in spark.table(f"followed_{other}").collect())
    assert found == {"click": [1, 2, 2], "none": []}
