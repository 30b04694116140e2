"""Edge lists, model weights and versioned adjacency in files."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh.functions.weights import Map
from graphrefresh.models import Layer, Model

EDGE = "src long, dst long, rel string, w double"


def read_edges(spark: SparkSession, path: str, kind: str = "csv", schema: str = EDGE, **options) -> DataFrame:
    """An edge list in CSV, JSON, Parquet or ORC; with a given schema no pass over the data infers one."""
    return spark.read.schema(schema).options(**options).format(kind).load(path)


def write_edges(edges: DataFrame, path: str, kind: str = "csv", **options) -> None:
    edges.select("src", "dst", "rel", "w").write.mode("overwrite").options(**options).format(kind).save(path)


def model_text(model: Model) -> str:
    return json.dumps({"name": model.name, "layers": [asdict(x) for x in model.layers]})


def model_of(text: str) -> Model:
    data = json.loads(text)
    maps = lambda ms: tuple(Map(m["name"], tuple(m["inputs"]), tuple(map(tuple, m["weights"]))) for m in ms)
    return Model(data["name"], tuple(Layer(**{k: maps(v) if k.endswith("_maps") else v for k, v in x.items()}) for x in data["layers"]))


def save_model(spark: SparkSession, model: Model, path: str) -> None:
    """One line of JSON, by the file system that Spark uses, so that any path of the cluster serves."""
    spark.createDataFrame([(model_text(model),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_model(spark: SparkSession, path: str) -> Model:
    return model_of("".join(r[0] for r in spark.read.text(path, wholetext=True).collect()))


class Adjacency:
    """Two copies of the edges, in buckets of the source and of the destination, each a base and runs of changes.

    A lookup by vertex reads its bucket only. Appending a batch writes one small run; ``compact`` folds runs into a new
    base under a new generation, so readers of the old one go on. Generations and runs are folders: there is no state
    outside them.
    """

    def __init__(self, spark: SparkSession, path: str, buckets: int = 64):
        self.spark, self.path, self.buckets = spark, path.rstrip("/"), buckets

    def _save(self, rows: DataFrame, folder: str) -> None:
        for side in ("src", "dst"):
            keyed = rows.withColumn("bucket", F.pmod(F.xxhash64(side), F.lit(self.buckets)).cast("int"))
            keyed.repartition("bucket").sortWithinPartitions("bucket", side).write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/{folder}/by_{side}")

    def create(self, edges: DataFrame) -> None:
        self._save(edges.select("src", "dst", "rel", "w", F.lit(1).alias("op"), F.lit(0).cast("long").alias("run")), "generation=0/run=0")

    def append(self, inserted: DataFrame, deleted: DataFrame, generation: int, run: int) -> None:
        """A batch as run ``run`` >= 1; written again it replaces itself."""
        row = lambda df, op: df.select("src", "dst", "rel", "w", F.lit(op).alias("op"), F.lit(run).cast("long").alias("run"))
        self._save(row(inserted, 1).unionByName(row(deleted, -1)), f"generation={generation}/run={run}")

    def edges(self, generation: int, runs: int, side: str = "src", of: list[int] | None = None) -> DataFrame:
        """The edges after the given number of runs, the last change of an edge holding; ``of`` names the buckets to read."""
        schema = "src long, dst long, rel string, w double, op int, run long, bucket int"
        rows = None
        for run in range(runs + 1):
            part = self.spark.read.schema(schema).parquet(f"{self.path}/generation={generation}/run={run}/by_{side}")
            part = part if of is None else part.where(F.col("bucket").isin(of))
            rows = part if rows is None else rows.unionByName(part)
        last = rows.groupBy("src", "dst", "rel").agg(F.max_by(F.struct("op", "w"), F.struct("run", "op")).alias("x"))
        return last.where("x.op = 1").select("src", "dst", "rel", "x.w")

    def bucket_of(self, vertices: DataFrame) -> list[int]:
        """The buckets that hold the given vertices: at most as many as there are buckets."""
        return sorted(r[0] for r in vertices.select(F.pmod(F.xxhash64("vid"), F.lit(self.buckets)).cast("int")).distinct().collect())

    def compact(self, generation: int, runs: int) -> int:
        """Fold all runs into the base of the next generation; its number."""
        self._save(self.edges(generation, runs).select("*", F.lit(1).alias("op"), F.lit(0).cast("long").alias("run")), f"generation={generation + 1}/run=0")
        return generation + 1
