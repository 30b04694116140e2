"""Epochs from a stream of updates: every micro-batch is netted, refreshed and written under its batch id."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh.models import Model
from graphrefresh.plans.cut import cut
from graphrefresh.plans.delta import refresh_from
from graphrefresh.plans.full import forward
from graphrefresh.sources.graphs import Batch, Graph, expanded, net
from graphrefresh.sources.store import Store, StoredFrames

#: ``op``: + and - of an edge; "set" gives the vertex ``src`` the features ``feat`` (and makes it, if new), "drop" deletes it.
UPDATE = "seq long, op string, src long, dst long, rel string, w double, ts timestamp, feat array<double>"


def updates(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Updates from a folder of Parquet files; a repeated sequence number within ten minutes of event time counts once."""
    rows = spark.readStream.schema(UPDATE).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return deduplicated(rows)


def deduplicated(rows: DataFrame) -> DataFrame:
    return rows.withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["seq"])


class Refresher:
    """Keeps a graph's embeddings fresh. Epoch e is a run of changes over epoch e - 1, so a batch that is run again overwrites its own result and nothing else.

    A batch costs what it changes: edges, states and embeddings are read by the buckets of the vertices it reaches.
    After every ``exact_every`` batches a complete pass makes a new base, which ends the drift of floating-point sums.
    """

    def __init__(self, graph: Graph, model: Model, path: str, rows_per_bucket: int = 1_000_000, max_runs: int = 16, exact_every: int | None = None):
        self.exact_every = exact_every
        self.model, self.store = model, Store.create(graph, model, path, -1, rows_per_bucket, max_runs)

    def on_batch(self, rows: DataFrame, batch_id: int) -> None:
        before = StoredFrames(self.store, batch_id - 1)
        b = batch_of(cut(rows), before)
        changes, _ = refresh_from(before, b, self.model)
        self.store.commit(b, changes, batch_id)
        if self.exact_every and (batch_id + 1) % self.exact_every == 0:
            now = self.store.graph(batch_id)
            now = Graph(cut(now.vertices), cut(now.edges))
            self.store.save(now, forward(now, self.model, write=True), batch_id)

    def run(self, stream: DataFrame, checkpoint: str) -> None:
        """Take in all that is there, then stop; a restart goes on after the last finished epoch."""
        stream.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()

    def embeddings(self, epoch: int) -> DataFrame:
        return self.store.outs[-1].at(epoch)


def batch_of(rows: DataFrame, before: StoredFrames) -> Batch:
    """The net effect of a micro-batch of updates on a stored graph. Edge updates go by sequence number; of several updates of one vertex the latest by event time, then sequence number, holds, also when it arrives late."""
    edges = rows.where("op IN ('+', '-')")
    inserted, deleted = net(before.out_edges(cut(edges.selectExpr("src AS vid").distinct())), edges)
    last = rows.where("op IN ('set', 'drop')").groupBy(F.col("src").alias("vid")).agg(F.max_by(F.struct("op", "feat"), F.struct("ts", "seq")).alias("x"))
    last = cut(last.select("vid", "x.op", "x.feat"))
    names = before.store.outs[0].columns[1:]
    changed = last.where("op = 'set'").select("vid", *[F.coalesce(F.get("feat", i), F.lit(0.0)).alias(c) for i, c in enumerate(names)])
    return expanded(None, Batch(cut(inserted), cut(deleted), changed, last.where("op = 'drop'").select("vid")), before)


def update_rates(stream: DataFrame, width: str = "5 minutes", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Updates by operation in tumbling, sliding or (given ``gap``) session windows of event time."""
    window = F.session_window("ts", gap) if gap else F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.groupBy(window.alias("window"), "op").agg(F.count(F.lit(1)).alias("updates"))


def files_for_bound(rate: float, rows_per_file: float, seconds: float) -> int:
    """Files a trigger for a latency bound, from a measured throughput of updates a second (see cost.bounded_throughput)."""
    return max(1, int(rate * seconds / max(rows_per_file, 1.0)))
