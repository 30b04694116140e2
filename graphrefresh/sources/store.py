"""Edges, states and embeddings in buckets on shared storage: a base and runs of changes, looked up by vertex."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh.models import Model
from graphrefresh.plans.cut import remove
from graphrefresh.plans.delta import KEY, Change, Frames, union
from graphrefresh.plans.full import LayerState, forward
from graphrefresh.sources.graphs import Batch, Graph


class Bucketed:
    """One table. A base has its rows in folders by bucket of ``by``, sorted by it; a run has the identities it replaces and their new rows.

    A lookup reads the buckets that hold a wanted vertex and the runs since the base, which are as large as the batches
    they came from. A base counts once its success marker is there; a run that is written again replaces itself.
    """

    def __init__(self, spark: SparkSession, path: str, schema: str, by: str, identity: list[str], buckets: int):
        self.spark, self.path, self.schema, self.by, self.identity, self.buckets = spark, path, schema, by, identity, buckets
        self.columns = [x.split()[0] for x in schema.split(", ")]
        self.touched = ", ".join(x for x in schema.split(", ") if x.split()[0] in identity)
        #: Buckets that lookups have read, for tests and reports.
        self.buckets_read = 0
        self._present: dict[int, set[int]] = {}

    def _names(self, path: str) -> list[str]:
        sc = self.spark.sparkContext
        target = sc._jvm.org.apache.hadoop.fs.Path(path)
        fs = target.getFileSystem(sc._jsc.hadoopConfiguration())
        return [f.getPath().getName() for f in fs.listStatus(target)] if fs.exists(target) else []

    def _bucket(self, column: str):
        return F.pmod(F.xxhash64(column), F.lit(self.buckets)).cast("int")

    def write_base(self, rows: DataFrame, epoch: int) -> None:
        keyed = rows.select(*self.columns, self._bucket(self.by).alias("bucket"))
        keyed.repartition(self.buckets, "bucket").sortWithinPartitions("bucket", self.by).write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/base={epoch}")
        self._present.pop(epoch, None)

    def write_run(self, touched: DataFrame, rows: DataFrame, epoch: int) -> None:
        tag = F.lit(epoch).cast("long").alias("run")
        touched.select(*self.identity).distinct().select("*", tag).write.mode("overwrite").parquet(f"{self.path}/run={epoch}/touched")
        rows.select(*self.columns, tag).write.mode("overwrite").parquet(f"{self.path}/run={epoch}/rows")

    def base_of(self, epoch: int) -> int:
        whole = [int(n[5:]) for n in self._names(self.path) if n.startswith("base=") and "_SUCCESS" in self._names(f"{self.path}/{n}")]
        return max(n for n in whole if n <= epoch)

    def at(self, epoch: int, of: DataFrame | None = None) -> DataFrame:
        """The rows at an epoch, all or those whose ``by`` is one of the vertices."""
        base = self.base_of(epoch)
        rows = self._base(base, of)
        runs = range(base + 1, epoch + 1)
        if not runs:
            return rows
        touched = self.spark.read.schema(self.touched + ", run long").parquet(*[f"{self.path}/run={r}/touched" for r in runs])
        newer = self.spark.read.schema(self.schema + ", run long").parquet(*[f"{self.path}/run={r}/rows" for r in runs])
        if of is not None and self.by in self.identity:
            touched, newer = (x.join(of.selectExpr("vid AS _k"), F.col(self.by) == F.col("_k"), "left_semi") for x in (touched, newer))
        last = touched.groupBy(*[F.col(c).alias(f"_{c}") for c in self.identity]).agg(F.max("run").alias("_run"))
        same = [F.col(c) == F.col(f"_{c}") for c in self.identity]
        kept = newer.join(last, [*same, F.col("run") == F.col("_run")], "left_semi").select(*self.columns)
        return rows.join(last, same, "left_anti").unionByName(kept)

    def _base(self, base: int, of: DataFrame | None) -> DataFrame:
        path = f"{self.path}/base={base}"
        read = self.spark.read.schema(self.schema + ", bucket int").option("basePath", path)
        if of is None:
            return read.parquet(path).select(*self.columns)
        if base not in self._present:
            self._present[base] = {int(n[7:]) for n in self._names(path) if n.startswith("bucket=")}
        wanted = sorted({r[0] for r in of.select(self._bucket("vid")).distinct().collect()} & self._present[base])  # numbers of buckets
        self.buckets_read += len(wanted)
        if not wanted:
            return self.spark.createDataFrame([], self.schema)
        rows = read.parquet(*[f"{path}/bucket={n}" for n in wanted])
        return rows.join(of.selectExpr("vid AS _k"), F.col(self.by) == F.col("_k"), "left_semi").select(*self.columns)


class Store:
    """A graph and the states of a model by epoch. ``rows_per_bucket`` sets the number of buckets when the store is made."""

    def __init__(self, spark: SparkSession, path: str, model: Model, features: int, buckets: int, max_runs: int = 16):
        self.spark, self.path, self.model, self.max_runs = spark, path.rstrip("/"), model, max_runs
        vector = lambda n: "vid long, " + ", ".join(f"h{i} double" for i in range(n))
        edge = "src long, dst long, rel string, w double"
        table = lambda name, schema, by, identity: Bucketed(spark, f"{self.path}/{name}", schema, by, identity, buckets)
        self.by_src, self.by_dst = table("by_src", edge, "src", KEY), table("by_dst", edge, "dst", KEY)
        self.outs, self.states = [table("out0", vector(features), "vid", ["vid"])], []
        for k, layer in enumerate(model.layers, 1):
            state = "vid long, rk string, " + ", ".join(f"s{i} double" for i in range(layer.state_width)) + ", n long"
            self.states.append(table(f"state{k}", state, "vid", ["vid"]))
            self.outs.append(table(f"out{k}", vector(len(layer.update)), "vid", ["vid"]))

    @property
    def tables(self) -> list[Bucketed]:
        return [self.by_src, self.by_dst, *self.outs, *self.states]

    @classmethod
    def create(cls, graph: Graph, model: Model, path: str, epoch: int = -1, rows_per_bucket: int = 1_000_000, max_runs: int = 16) -> Store:
        spark = graph.vertices.sparkSession
        buckets = max(1, min(4096, -(-graph.edges.count() // rows_per_bucket)))
        store = cls(spark, path, model, len(graph.vertices.columns) - 1, buckets, max_runs)
        store.save(graph, forward(graph, model, write=True), epoch)
        return store

    def save(self, graph: Graph, states: list[LayerState], epoch: int) -> None:
        """A new base of every table."""
        for table in (self.by_src, self.by_dst):
            table.write_base(graph.edges, epoch)
        self.outs[0].write_base(graph.vertices, epoch)
        for k, s in enumerate(states):
            self.states[k].write_base(s.state, epoch)
            self.outs[k + 1].write_base(s.out, epoch)

    def commit(self, b: Batch, changes: list[Change], epoch: int) -> None:
        """An expanded batch and what it changed, as a run; now and then the runs are folded into a new base."""
        moved = union(b.inserted.select(*KEY), b.deleted.select(*KEY))
        for table in (self.by_src, self.by_dst):
            table.write_run(moved, b.inserted, epoch)
        gone = b.removed.select("vid")
        self.outs[0].write_run(union(b.changed.select("vid"), gone), b.changed, epoch)
        for k, c in enumerate(changes):
            self.states[k].write_run(c.touched, c.state, epoch)
            self.outs[k + 1].write_run(union(c.out.select("vid"), gone), c.out, epoch)
        if epoch - self.by_src.base_of(epoch) >= self.max_runs:
            self.compact(epoch)

    def compact(self, epoch: int) -> None:
        for table in self.tables:
            table.write_base(table.at(epoch), epoch)

    def drop_before(self, epoch: int) -> None:
        """Delete bases and runs that no reader of ``epoch`` or later needs."""
        for table in self.tables:
            keep = table.base_of(epoch)
            for name in table._names(table.path):
                kind, _, n = name.partition("=")
                if (kind == "base" and int(n) < keep) or (kind == "run" and int(n) <= keep):
                    remove(self.spark, f"{table.path}/{name}")

    def graph(self, epoch: int) -> Graph:
        return Graph(self.outs[0].at(epoch), self.by_src.at(epoch))


class StoredFrames(Frames):
    """Lookups in a store as it was at an epoch."""

    def __init__(self, store: Store, epoch: int):
        self.store, self.epoch, self.complete = store, epoch, True

    def out_edges(self, of: DataFrame) -> DataFrame:
        return self._edges(self.store.by_src, of)

    def in_edges(self, of: DataFrame) -> DataFrame:
        return self._edges(self.store.by_dst, of)

    def _edges(self, table: Bucketed, of: DataFrame) -> DataFrame:
        rows = table.at(self.epoch, of)
        return rows.join(of.selectExpr("vid AS _k"), F.col(table.by) == F.col("_k"), "left_semi")

    def out(self, k: int, of: DataFrame) -> DataFrame:
        return self.store.outs[k].at(self.epoch, of)

    def state(self, k: int, of: DataFrame) -> DataFrame:
        return self.store.states[k - 1].at(self.epoch, of)
