"""Graphs and update batches from the relational tables."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphrefresh.operators.joins import nearest
from graphrefresh.plans.cut import beside, cut


@dataclass(frozen=True)
class Graph:
    """``edges``: src, dst, rel, w; ``vertices``: vid, h0.. (the features, of any width)."""

    vertices: DataFrame
    edges: DataFrame


@dataclass(frozen=True)
class Batch:
    """Net effect of updates: edges that appear and disappear, vertices with new features, that are new or deleted; ``complete`` says that it is ``expanded``."""

    inserted: DataFrame
    deleted: DataFrame
    changed: DataFrame
    removed: DataFrame
    complete: bool = False


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return rows.select(*columns) if columns else rows


def share(*parts) -> Column:
    """A number from 0 to 1 that depends on nothing but the values."""
    text = F.concat_ws("-", *[p if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / 4294967296.0


def _both_ways(pairs: DataFrame, there: str, back: str) -> DataFrame:
    """Undirected pairs (a, b, ts) as edges in both directions."""
    a = pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(there).alias("rel"), "ts")
    return a.unionByName(pairs.select(F.col("b").alias("src"), F.col("a").alias("dst"), F.lit(back).alias("rel"), "ts"))


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_shipdate")
    pairs = rows.groupBy((4 * F.col("l_orderkey")).alias("a"), (4 * F.col("l_partkey") + 1).alias("b")).agg(F.min("l_shipdate").alias("ts"))
    return _both_ways(pairs, "contains", "in_order")


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").join(table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    pairs = rows.groupBy((4 * F.col("o_custkey") + 2).alias("a"), (4 * F.col("l_partkey") + 1).alias("b")).agg(F.min("o_orderdate").alias("ts"))
    return _both_ways(pairs, "contains", "in_order")


def supp_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey", "l_shipdate")
    pairs = rows.groupBy((4 * F.col("l_suppkey") + 3).alias("a"), (4 * F.col("l_partkey") + 1).alias("b")).agg(F.min("l_shipdate").alias("ts"))
    return _both_ways(pairs, "contains", "in_order")


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").distinct()
    dated = rows.join(table(spark, sf_dir, "orders", "o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_partkey", "o_orderdate")
    other = rows.select(F.col("l_orderkey").alias("o2"), F.col("l_partkey").alias("p2"))
    pairs = dated.join(other, (F.col("l_orderkey") == F.col("o2")) & (F.col("l_partkey") != F.col("p2")))
    return pairs.groupBy((4 * F.col("l_partkey") + 1).alias("src"), (4 * F.col("p2") + 1).alias("dst")).agg(F.lit("contains").alias("rel"), F.min("o_orderdate").alias("ts")).select("src", "dst", "rel", "ts")


def typed(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = table(spark, sf_dir, "orders", "o_custkey", "o_orderkey", "o_orderdate").groupBy((4 * F.col("o_custkey") + 2).alias("a"), (4 * F.col("o_orderkey")).alias("b")).agg(F.min("o_orderdate").alias("ts"))
    return order_part(spark, sf_dir).unionByName(_both_ways(placed, "placed", "placed_by"))


def transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed: from each item of a user to the next one."""
    rows = table(spark, sf_dir, "events", "event_id", "user_id", "props", "ts").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    nxt = F.lead("k").over(Window.partitionBy("user_id").orderBy("event_id"))
    pairs = rows.select(F.col("k").alias("src"), nxt.alias("dst"), "ts").where("dst IS NOT NULL")
    return pairs.groupBy("src", "dst").agg(F.lit("contains").alias("rel"), F.min("ts").alias("ts"))


def user_item(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "events", "user_id", "props", "ts").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    pairs = rows.groupBy((2 * F.col("user_id")).alias("a"), (2 * F.col("k") + 1).alias("b")).agg(F.min("ts").alias("ts"))
    return _both_ways(pairs, "contains", "in_order")


def _synthetic(src: Column, dst: Column) -> Column:
    """A moment for an edge that has none: a day of 2024 and its seconds, from md5."""
    return F.timestamp_seconds(F.lit(1_704_067_200) + F.floor(share("t", src, dst) * 31_536_000))


def knn(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """Directed: to each vector from its nearest by cosine."""
    near = nearest(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), k)
    return near.select(F.col("vec_id").alias("src"), F.col("query").alias("dst"), F.lit("contains").alias("rel"), _synthetic(F.col("vec_id"), F.col("query")).alias("ts"))


def doc_token(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and the words of 3 to 12 characters in them, A-Z in lower case; a word's id is 52 bits of its md5."""
    low = F.translate(F.coalesce("text", F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    words = table(spark, sf_dir, "documents", "doc_id", "text").select((2 * F.col("doc_id")).alias("a"), F.explode(F.array_distinct(F.split(low, " +"))).alias("t"))
    pairs = words.where(F.length("t").between(3, 12)).select("a", (2 * F.conv(F.substring(F.md5("t"), 1, 13), 16, 10).cast("long") + 1).alias("b")).distinct()
    return _both_ways(pairs.withColumn("ts", _synthetic(F.col("a"), F.col("b"))), "contains", "in_order")


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed: from each turn of a conversation to the next; an id is the conversation's times 1024, and the turn."""
    rows = table(spark, sf_dir, "conversations", "conv_id", "turn")
    nxt = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    pairs = rows.select(F.col("conv_id"), "turn", nxt.alias("next")).where("next IS NOT NULL")
    vid = lambda c: F.col("conv_id") * 1024 + F.col(c)
    return pairs.select(vid("turn").alias("src"), vid("next").alias("dst"), F.lit("contains").alias("rel"), F.timestamp_seconds("turn").alias("ts")).distinct()


EDGES = {"knn": knn, "doc_token": doc_token, "turns": turns, "order_part": order_part, "cust_part": cust_part, "supp_part": supp_part, "copurchase": copurchase, "typed": typed, "transitions": transitions, "user_item": user_item}


def with_weights(edges: DataFrame) -> DataFrame:
    return edges.withColumn("w", (F.pmod(F.col("src") + F.col("dst"), F.lit(4)) + 1) / 4.0)


def features(vid: Column) -> list[Column]:
    """Dyadic features from the id alone."""
    return [(F.pmod(vid, F.lit(64)) / 64.0).alias("h0"), (F.pmod(F.floor(vid / 3), F.lit(16)) / 16.0).alias("h1"), (F.pmod(vid, F.lit(7)) / 8.0).alias("h2"), F.lit(1.0).alias("h3")]


def vertices_of(edges: DataFrame) -> DataFrame:
    ids = edges.select(F.col("src").alias("vid")).union(edges.select(F.col("dst").alias("vid"))).distinct()
    return ids.select("vid", *features(F.col("vid")))


def split(edges: DataFrame, base_share: float = 0.9, grain: int = 3_600_000_000) -> tuple[DataFrame, DataFrame]:
    """Oldest edges and newest edges, cut at a quantile of the timestamp; edges of the cut's own instant are old.

    The quantile is found in a histogram of ``grain`` microseconds, then exactly inside the one step that holds it, so no
    task holds all timestamps; one number comes to the driver.
    """
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    steps = edges.groupBy(F.floor(us / grain).alias("step")).agg(F.count(F.lit(1)).alias("n"))  # a row an hour
    upto, place = F.sum("n").over(Window.orderBy("step")), F.ceil(F.lit(base_share) * F.sum("n").over(Window.partitionBy(F.lit(1))))
    here = steps.select("step", "n", upto.alias("upto"), place.alias("place")).where("upto >= place AND upto - n < place").first()
    if here is None:
        return edges, edges.limit(0)
    inside = edges.where(F.floor(us / grain) == here.step).groupBy(us.alias("us")).agg(F.count(F.lit(1)).alias("n"))
    inside = inside.select("us", F.sum("n").over(Window.orderBy("us")).alias("upto"))
    at = inside.where(F.col("upto") >= here.place - here.upto + here.n).agg(F.min("us")).first()[0]
    return edges.where(us <= at), edges.where(us > at)


def _pair_share(tag: str) -> Column:
    return share(tag, F.least("src", "dst"), F.greatest("src", "dst"))


def snapshot(spark: SparkSession, sf_dir: str, name: str) -> tuple[Graph, DataFrame]:
    """The graph of the oldest edges, on the vertices of all edges, and the stream of the newest."""
    edges = cut(with_weights(EDGES[name](spark, sf_dir)), probed=True)
    base, stream = split(edges)
    return Graph(vertices_of(edges), base.drop("ts")), stream.drop("ts")


def batch(graph: Graph, stream: DataFrame, inserts: float = 0.02, deletes: float = 0.002, changes: float = 0.0, removals: float = 0.0) -> Batch:
    """Shares of the stream to insert, of the base to delete, of the vertices to change or remove, all drawn by md5."""
    ins, dele = stream.where(_pair_share("i") < inserts), graph.edges.where(_pair_share("d") < deletes)
    changed = graph.vertices.where(share("f", F.col("vid")) < changes).withColumn("h2", F.col("h2") + 0.5)
    removed = graph.vertices.where(share("v", F.col("vid")) < removals).select("vid")
    if removals:
        gone = lambda e, side: e.join(removed.select(F.col("vid").alias(side)), side, "left_semi")
        dele = dele.unionByName(gone(graph.edges, "src")).unionByName(gone(graph.edges, "dst")).distinct()
        keep = lambda e, side: e.join(removed.select(F.col("vid").alias(side)), side, "left_anti")
        ins, changed = keep(keep(ins, "src"), "dst").select(*ins.columns), keep(changed, "vid").select(*changed.columns)
    return Batch(ins, dele.select(*graph.edges.columns), changed, removed)


def out_of(edges: DataFrame, vertices: DataFrame, side: str = "src") -> DataFrame:
    """The edges whose ``side`` is one of the vertices."""
    return edges.join(beside(vertices.selectExpr("vid AS _k")), F.expr(f"{side} = _k"), "left_semi")


def expanded(graph: Graph, b: Batch, lookup=None) -> Batch:
    """The batch with what it implies: edges of removed vertices are deleted, new edges to them dropped, and unknown ends of new edges become vertices with zero features.

    ``lookup`` finds the graph's rows instead, where they are not whole tables (see plans.delta.Frames). A batch that was
    expanded for this graph before is returned as it is.
    """
    if b.complete:
        return b
    vertices = (lambda of: lookup.out(0, of)) if lookup else lambda of: graph.vertices.join(beside(of), "vid", "left_semi")
    inserted, deleted, changed = b.inserted, b.deleted, b.changed
    if not b.removed.isEmpty():
        away = lambda rows, *sides: reduce(lambda r, side: r.join(b.removed.selectExpr("vid AS _k"), F.expr(f"{side} = _k"), "left_anti"), sides, rows)
        incident = lookup.in_edges(b.removed).unionByName(lookup.out_edges(b.removed)) if lookup else out_of(graph.edges, b.removed, "dst").unionByName(out_of(graph.edges, b.removed))
        deleted = cut(deleted.unionByName(incident).dropDuplicates(["src", "dst", "rel"]))
        inserted, changed = cut(away(inserted, "src", "dst")), away(changed, "vid")
    ends = inserted.selectExpr("src AS vid").union(inserted.selectExpr("dst AS vid"))
    unknown = ends.distinct().join(vertices(ends).select("vid"), "vid", "left_anti").join(beside(changed.select("vid")), "vid", "left_anti")
    changed = cut(changed.unionByName(unknown.selectExpr("vid", *[f"0e0 AS {c}" for c in changed.columns if c != "vid"])))
    # what is known to be empty is planned away
    empty = lambda df: df.limit(0) if df.isEmpty() else df
    return Batch(inserted, empty(deleted), empty(changed), b.removed, complete=True)


def apply(graph: Graph, b: Batch) -> Graph:
    """The graph after a batch that is ``expanded``."""
    key = ["src", "dst", "rel"]
    edges = graph.edges.join(beside(b.deleted.select(*key)), key, "left_anti").select(*graph.edges.columns).unionByName(b.inserted)
    vertices = graph.vertices.join(beside(b.changed.select("vid")), "vid", "left_anti").unionByName(b.changed).join(beside(b.removed), "vid", "left_anti")
    return replace(graph, vertices=vertices, edges=edges)


def net(edges: DataFrame, updates: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(inserted, deleted) of updates (seq, op, src, dst, rel, w): the last operation on an edge holds; inserting what is there and deleting what isn't do nothing."""
    key = ["src", "dst", "rel"]
    last = updates.groupBy(*key).agg(F.max_by(F.struct("op", "w"), "seq").alias("x")).select(*key, "x.op", "x.w")
    there = edges.select(*key)
    return last.where("op = '+'").join(there, key, "left_anti").select(*key, "w"), last.where("op = '-'").join(there, key, "left_semi").select(*key, "w")

