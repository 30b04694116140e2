"""The experiments: sweeps over batch size, queries, depth, evicted state and chunks; trained heads; checks of models."""

from __future__ import annotations

from collections.abc import Callable
from functools import cache, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh.models import WIDTH, ZOO, model
from graphrefresh.operators import windows
from graphrefresh.plans import baselines, catalogue, chunk, cost, twohop, upkeep, verify
from graphrefresh.plans.cut import cut
from graphrefresh.plans.delta import Refresh, ids, refresh
from graphrefresh.plans.full import H, LayerState, forward
from graphrefresh.sources import graphs
from graphrefresh.sources.graphs import Batch, Graph

SMALL = {"inserts": 0.002, "deletes": 0.0002}
FEW = {"inserts": 0.0005, "deletes": 0.002}
CHUNKS = (512, 2048, 8192, 32768)


def _union(rows: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, rows)


def _tagged(df: DataFrame, **tags) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in tags.items()], "*")


def _ready(spark: SparkSession, sf: str, graph: str) -> tuple[Graph, DataFrame]:
    g, stream = graphs.snapshot(spark, sf, graph)
    return Graph(cut(g.vertices, probed=True), g.edges), stream


def _batch(g: Graph, stream: DataFrame, shares: dict) -> Batch:
    b = graphs.batch(g, stream, **shares)
    return Batch(cut(b.inserted), cut(b.deleted), cut(b.changed), cut(b.removed))


def _settled(g: Graph, m) -> list[LayerState]:
    return forward(g, m, write=True)


def _total(runs: dict[str, Refresh]) -> DataFrame:
    return cost.traces(runs).groupBy("method").agg(F.count(F.lit(1)).alias("edges"))


def two_hop_delta(spark: SparkSession, sf: str) -> DataFrame:
    g, stream = _ready(spark, sf, "transitions")
    b = _batch(g, stream, {"inserts": 0.05, "deletes": 0.01})
    return twohop.two_hop_delta(g.edges, twohop.two_hop(g.edges), b.inserted, b.deleted)


def conditions_report(spark: SparkSession, sf: str) -> DataFrame:
    """Which models meet which condition on states whose numbers are those of the given vectors."""
    vectors = graphs.table(spark, sf, "embeddings", "vec_id", "embedding")
    return _union([_tagged(verify.conditions(spark, make(1), vectors=vectors), model=name) for name, make in ZOO.items()])


def equivalence_report(spark: SparkSession, sf: str) -> DataFrame:
    """Incremental against whole passes on drawn graphs; ``sf`` is not read."""
    return _union([verify.equivalence(spark, model(n), [1, 2]) for n in ("gcn", "gin", "gat")])


def custom_model(spark: SparkSession, sf: str) -> DataFrame:
    """A model put together from the catalogue's parts, checked and refreshed."""
    layers = tuple(catalogue.decompose("weighted_mean", [f"h{i}" for i in range(WIDTH)], [f"greatest(a{i}, 0e0)" for i in range(WIDTH)], "w") for _ in range(2))
    m = verify.Model("weighted_mean", layers)
    g, stream = _ready(spark, sf, "transitions")
    b = _batch(g, stream, {"inserts": 0.05, "deletes": 0.01, "changes": 0.02})
    done, incremental = verify.checked_refresh(g, _settled(g, m), b, m)
    return cost.mse(done.embeddings, baselines.whole_graph(g, b, m).embeddings).select((F.col("max_abs") < 1e-9).alias("equal"), "vertices", F.lit(incremental).alias("incremental"))


def drift_audit(spark: SparkSession, sf: str) -> DataFrame:
    """Drift of the sums after five batches that follow each other."""
    g, stream = _ready(spark, sf, "transitions")
    m = model("gcn")
    states, cuts = _settled(g, m), windows.batches(stream, 5, F.col("src") % 16, "src", "dst")
    cuts = cut(cuts)
    for k in range(5):
        none = g.vertices.limit(0)
        done = refresh(g, states, Batch(cuts.where(F.col("batch") == k).drop("batch"), g.edges.where(graphs.share(f"x{k}", "src", "dst") < 0.01), none, ids(none)), m)
        g, states = Graph(cut(done.graph.vertices), cut(done.graph.edges)), done.states
    return upkeep.audit(g, states, m, 0.25)


def sweep_batch_size(spark: SparkSession, sf: str) -> DataFrame:
    """``updates, method, edges, seconds``: batches of 1 to 10,000 new edges and of the whole stream, on the same base."""
    g, stream = _ready(spark, sf, "order_part")
    m, out = model("sage_mean"), []
    states, pick = _settled(g, m), cut(stream)
    none = g.vertices.limit(0)
    for n in (1, 10, 100, 1000, 10_000, None):
        b = Batch(pick if n is None else cut(pick.orderBy(graphs.share("b", "src", "dst"), "src", "dst").limit(n)), g.edges.limit(0), none, ids(none))
        runs, seconds = {}, {}
        seconds["delta"] = cost.timed(lambda: runs.setdefault("delta", refresh(g, states, b, m)).embeddings)
        changed = runs["delta"].changed
        seconds["cache_reuse"] = cost.timed(lambda: runs.setdefault("cache_reuse", baselines.cache_reuse(g, states, b, m, changed)).embeddings)
        seconds["full_neighbour"] = cost.timed(lambda: runs.setdefault("full_neighbour", baselines.full_neighbour(g, b, m, changed[-1])).embeddings)
        took = F.create_map(*[F.lit(x) for kv in seconds.items() for x in kv])
        out.append(_tagged(_total(runs).withColumn("seconds", took[F.col("method")]), updates=str(n or "all")))
    return _union(out)


def sweep_queries(spark: SparkSession, sf: str) -> DataFrame:
    """``queries, edges``: the work of on-demand refreshes for more and more of the affected vertices."""
    g, stream = _ready(spark, sf, "order_part")
    m, b, out = model("sage_mean"), _batch(g, stream, SMALL), []
    states = _settled(g, m)
    done = refresh(g, states, b, m)
    order = graphs.share("q", "vid")
    for n in (1, 10, 100, None):
        queries = cut(done.changed[-1] if n is None else done.changed[-1].orderBy(order).limit(n))
        _, run = baselines.on_demand(g, states, b, m, queries)
        out.append(_tagged(_total({"on_demand": run}), queries=str(n or "all")))
    return _union(out)


def sweep_depth(spark: SparkSession, sf: str) -> DataFrame:
    """``depth, method, edges`` for two and three layers."""
    g, stream = _ready(spark, sf, "order_part")
    b, out = _batch(g, stream, FEW), []
    for depth in (2, 3):
        m = model("sage_mean", depth)
        states = _settled(g, m)
        done = refresh(g, states, b, m)
        out.append(_tagged(_total({"delta": done, "cache_reuse": baselines.cache_reuse(g, states, b, m, done.changed), "full_neighbour": baselines.full_neighbour(g, b, m, done.changed[-1])}), depth=depth))
    return _union(out)


def sweep_eviction(spark: SparkSession, sf: str) -> DataFrame:
    """``kept, edges``: the work of a refresh when the sums of the least connected vertices are gone."""
    g, stream = _ready(spark, sf, "order_part")
    m, b, out = model("sage_mean"), _batch(g, stream, SMALL), []
    states = _settled(g, m)
    for fraction in (1.0, 0.9, 0.5):
        some, kept = upkeep.evict(g, states, fraction)
        out.append(_tagged(_total({"delta": refresh(g, some, b, m, stored=[cut(k) for k in kept])}), kept=fraction))
    return _union(out)


def sweep_chunk(spark: SparkSession, sf: str) -> DataFrame:
    edges = cut(graphs.order_part(spark, sf).select("src", "dst"))
    return _union([_tagged(chunk.loads(chunk.plan(edges, n)), max_edges=n) for n in CHUNKS])


def guard_overhead(spark: SparkSession, sf: str) -> DataFrame:
    """``model, edges, vertices, seconds`` and the same ``unguarded``: what summing readers of their own embedding anew adds to the signed messages; seconds depend on the machine."""
    g, stream = _ready(spark, sf, "order_part")
    b, rows = _batch(g, stream, SMALL), {}
    for name in ("sage_mean", "gat", "agnn"):
        m, runs = model(name), {}
        states = _settled(g, m)
        seconds = cost.timed(lambda: runs.setdefault("d", refresh(g, states, b, m)).changes[-1].front)
        trace = cut(cost.traces(runs))
        rows[name] = (trace.count(), cost.vertex_accesses(trace).agg(F.sum("vertices")).first()[0], seconds)
    plain = rows.pop("sage_mean")
    return spark.createDataFrame([(n, *r, *plain) for n, r in rows.items()], "model string, edges long, vertices long, seconds double, unguarded_edges long, unguarded_vertices long, unguarded_seconds double")


def constmsg_edges(spark: SparkSession, sf: str) -> DataFrame:
    """``model, constant_messages, edges, delta_edges``: edges that a system for constant messages processes, beside the incremental refresh."""
    g, stream = _ready(spark, sf, "order_part")
    b, out = _batch(g, stream, SMALL), []
    for name in ("sage_sum", "sage_mean"):
        m = model(name)
        states = _settled(g, m)
        run, kept = baselines.const_message_delta(g, states, b, m)
        own = run if kept else refresh(g, states, b, m)
        counts = _total({"const": run, "delta": own}).groupBy().pivot("method", ["const", "delta"]).agg(F.sum("edges"))
        out.append(_tagged(counts.select(F.col("const").alias("edges"), F.col("delta").alias("delta_edges")), model=name, constant_messages=kept))
    return _union(out)


def phase_times(spark: SparkSession, sf: str, graph: str = "order_part", name: str = "sage_mean") -> DataFrame:
    """``method, phase, seconds, share``: finding what a batch affects, getting the edges to process, computing with them; seconds depend on the machine."""
    g, stream = _ready(spark, sf, graph)
    m, b = model(name), _batch(g, stream, SMALL)
    states = _settled(g, m)

    def found():
        return baselines.reach(g, graphs.expanded(g, b), m)

    def out_edges() -> DataFrame:
        return _union([graphs.out_of(g.edges, f) for f in found()[:-1]] + [b.inserted, b.deleted])

    def in_edges() -> DataFrame:
        need, new, parts = found()[-1], graphs.apply(g, graphs.expanded(g, b)), []
        for _ in m.layers:
            parts.append(cut(graphs.out_of(new.edges, need, "dst")))
            need = ids(parts[-1], "src").distinct()
        return _union(parts)

    detect = lambda: found()[-1]
    steps = {
        "delta": {"detect": detect, "construct": out_edges, "compute": lambda: refresh(g, states, b, m).changes[-1].front},
        "full_neighbour": {"detect": detect, "construct": in_edges, "compute": lambda: baselines.full_neighbour(g, b, m, found()[-1]).embeddings},
    }
    rows = []
    for method, todo in steps.items():
        took = cost.phases(todo)
        rows += [(method, phase, s, s / max(sum(took.values()), 1e-9)) for phase, s in took.items()]
    return spark.createDataFrame(rows, "method string, phase string, seconds double, share double")


def hundred_batches(spark: SparkSession, sf: str, graph: str) -> tuple[DataFrame, DataFrame]:
    """The oldest nine tenths of a graph's edges, and the rest in a hundred batches by time (column ``batch``)."""
    edges = cut(graphs.EDGES[graph](spark, sf).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))))
    base, stream = graphs.split(edges)
    cuts = windows.batches(stream, 100, F.floor(F.col("us") / 3_600_000_000), "us", "src", "dst")
    return base.select("src", "dst"), cut(cuts.select("batch", "src", "dst"))


def batch_accesses(base: DataFrame, moved: DataFrame, depth: int = 2) -> DataFrame:
    """``batch, delta, cache_reuse, full_neighbour``: edges that each method processes for every batch of new edges, each on the base alone, for a model that reads neither the destination nor degrees nor itself.

    All batches go through the same joins, with the batch as part of the key: what they reach is told apart, the graph is
    read once. A vertex's number of in-edges stands for its in-edges, so no edge is enumerated for the counts of a layer.
    """
    key = ["batch", "vid"]
    deg = base.groupBy(F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("n"))
    more = moved.groupBy("batch", F.col("dst").alias("vid")).agg(F.count(F.lit(1)).alias("m"))
    full = lambda vs: vs.join(deg, "vid", "left").join(more, key, "left").groupBy("batch").agg(F.sum(F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))).alias("edges"))
    new = moved.groupBy("batch").agg(F.count(F.lit(1)).alias("edges"))
    ends = moved.select("batch", F.col("dst").alias("vid")).distinct()
    counts, front = [], None
    fan = base.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("n"))
    for _ in range(depth):
        counts.append(_tagged(new, method="delta"))
        if front is not None:
            counts.append(_tagged(front.join(fan, "vid").groupBy("batch").agg(F.sum("n").alias("edges")), method="delta"))
            reached = front.join(base.select(F.col("src").alias("vid"), "dst"), "vid").select("batch", F.col("dst").alias("vid"))
            front = cut(reached.unionByName(ends).distinct())
        else:
            front = cut(ends)
        counts.append(_tagged(full(front), method="cache_reuse"))
    need = front
    for k in range(depth):
        counts.append(_tagged(full(need), method="full_neighbour"))
        if k < depth - 1:
            below = need.join(base.select(F.col("dst").alias("vid"), "src"), "vid").select("batch", F.col("src").alias("vid"))
            new_below = need.join(moved.select("batch", F.col("dst").alias("vid"), "src"), key).select("batch", F.col("src").alias("vid"))
            need = cut(below.unionByName(new_below).distinct())
    return _union(counts).groupBy("batch").pivot("method", ["delta", "cache_reuse", "full_neighbour"]).agg(F.sum("edges"))


def redundancy_by_batch(spark: SparkSession, sf: str) -> DataFrame:
    """``graph, batch, delta, cache_reuse, full_neighbour``: edges processed for each of the hundred batches of the newest tenth of three graphs."""
    return _union([_tagged(batch_accesses(*hundred_batches(spark, sf, g)), graph=g) for g in REDUNDANCY_GRAPHS])


REDUNDANCY_GRAPHS = ("order_part", "user_item", "transitions")


def chosen_batches(spark: SparkSession, sf: str, graph: str, inserts: int = 50) -> tuple[Graph, Callable[[str], Batch]]:
    """A graph and, by seed, a batch of ``inserts`` edges that appear and as many that disappear; a batch is picked once, whoever asks for it."""
    g, stream = _ready(spark, sf, graph)
    none = g.vertices.limit(0)

    @cache
    def batch(seed: str) -> Batch:
        pick = cut(stream.orderBy(graphs.share(seed, "src", "dst"), "src", "dst").limit(inserts))
        drop = cut(g.edges.orderBy(graphs.share(f"{seed}d", "src", "dst"), "src", "dst").limit(inserts))
        return Batch(pick, drop, none, ids(none))

    return g, batch


def prepared_runs(spark: SparkSession, sf: str, graph: str, name: str, inserts: int = 50, chosen: tuple[Graph, Callable[[str], Batch]] | None = None):
    """A settled graph and model and, batch by batch, one refresh of each method: (method, updates, run) with nothing but the refresh inside run. Models of one graph may share what is ``chosen``."""
    g, batch = chosen or chosen_batches(spark, sf, graph, inserts)
    m = model(name)
    states = _settled(g, m)

    def methods(seed: str) -> dict:
        b = batch(seed)

        def reached() -> tuple[Batch, list[DataFrame]]:
            whole = graphs.expanded(g, b)
            return whole, baselines.reach(g, whole, m)

        def reuse() -> DataFrame:
            whole, fronts = reached()
            return baselines.cache_reuse(g, states, whole, m, fronts).states[-1].state

        def neighbours(fanout: int | None = None) -> DataFrame:
            whole, fronts = reached()
            return baselines.full_neighbour(g, whole, m, fronts[-1], fanout).embeddings

        return {
            "delta": lambda: refresh(g, states, b, m).changes[-1].front,
            "cache_reuse": reuse,
            "full_neighbour": neighbours,
            "sampled_5": lambda: neighbours(5),
            "sampled_10": lambda: neighbours(10),
            "whole_graph": lambda: baselines.whole_graph(g, b, m).embeddings,
        }

    return methods, 2 * inserts


def response_times(spark: SparkSession, sf: str, graphs_of: tuple = ("order_part",), models: tuple = ("gcn", "gat"), methods: tuple = ("delta", "cache_reuse", "full_neighbour", "sampled_5", "whole_graph"), runs: int = 2) -> DataFrame:
    """``graph, model, method, seconds, throughput, speedup``: mean seconds of a refresh over ``runs`` batches after one to warm up, updated edges a second, and how many times as long as the incremental refresh it takes.

    Every method has to find what a batch affects; the whole graph doesn't. ``seconds`` depend on the machine.
    """
    rows = []
    for graph in graphs_of:
        chosen = chosen_batches(spark, sf, graph)
        for name in models:
            make, updates = prepared_runs(spark, sf, graph, name, chosen=chosen)
            took: dict[str, list[float]] = {x: [] for x in methods}
            for r in range(runs + 1):
                todo = make(f"time{r}")
                for x in methods:
                    took[x].append(cost.timed(todo[x]))
            mean = {x: sum(ts[1:]) / runs for x, ts in took.items()}
            rows += [(graph, name, x, s, cost.throughput(updates, s), cost.speedup(s, mean["delta"])) for x, s in mean.items()]
    return spark.createDataFrame(rows, "graph string, model string, method string, seconds double, throughput double, speedup double")


def latency_bounds(spark: SparkSession, sf: str, bounds: tuple = (1.0, 5.0, 25.0, 50.0, 100.0), sizes: tuple = (10, 1000), runs: int = 2) -> DataFrame:
    """``bound, updates, throughput``: for each latency bound the largest batch all of whose runs keep it, and its worst throughput."""
    def seconds(n: int) -> list[float]:
        make, _ = prepared_runs(spark, sf, "order_part", "gcn", n // 2)
        return [cost.timed(make(f"bound{r}")["delta"]) for r in range(runs)]
    return spark.createDataFrame(cost.bounded_throughput(seconds, list(sizes), list(bounds)), "bound double, updates long, throughput double")


def analytic_costs(spark: SparkSession, sf: str) -> DataFrame:
    """``method, edges``: the cost formulas with mean degree, updates and fan-out as measured on a batch."""
    g, stream = _ready(spark, sf, "order_part")
    b, m = _batch(g, stream, SMALL), model("sage_mean")
    done = refresh(g, _settled(g, m), b, m)
    updated = b.inserted.count() + b.deleted.count()
    sizes = [c.count() for c in done.changed]
    alpha = sizes[1] / max(sizes[0], 1)
    d = g.edges.count() / max(g.vertices.count(), 1)
    return spark.createDataFrame([(k, round(float(v), 3)) for k, v in cost.analytic(d, updated, alpha, 2, min(alpha, 5.0)).items()], "method string, edges double")


def trained_heads(spark: SparkSession, sf: str) -> DataFrame:
    """``approach, accuracy, sd`` of a classifier over five splits: refitted on the new embeddings, or fitted on the old and given refreshed, sampled or old ones."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    g, stream = _ready(spark, sf, "transitions")
    m = model("sage_mean")
    b = _batch(g, stream, {"inserts": 0.5, "deletes": 0.05, "changes": 0.2})
    states = _settled(g, m)
    flipped = lambda h: cost.label(h).withColumn("y", F.when(graphs.share("flip", F.col("vid")) < 0.05, F.pmod(F.col("y") + 1, F.lit(WIDTH))).otherwise(F.col("y")))
    assembled = VectorAssembler(inputCols=H, outputCol="features").transform
    done = refresh(g, states, b, m)
    new, old = done.embeddings, states[-1].out
    truth = {"old": cut(flipped(old)), "new": cut(flipped(baselines.whole_graph(g, b, m).embeddings))}
    seen = {"retrain": new, "delta": new, "periodic": old} | {f"sampled_{k}": baselines.full_neighbour(g, b, m, ids(g.vertices), k).embeddings for k in (5, 10, 20)}
    seen = {n: cut(h) for n, h in seen.items()}
    rows = []
    for run in range(5):
        u = graphs.share(f"split{run}", F.col("vid"))
        fit = lambda h, y, u=u: LogisticRegression(labelCol="y", maxIter=30).fit(assembled(h.join(y, "vid").where(u < 0.25)))
        heads = {"old": fit(old, truth["old"]), "new": fit(new, truth["new"])}
        for name, h in seen.items():
            got = heads["new" if name == "retrain" else "old"].transform(assembled(h.join(truth["new"], "vid").where(u >= 0.5)))
            rows.append(got.agg(F.avg((F.col("prediction") == F.col("y")).cast("double")).alias("a")).select(F.lit(name).alias("approach"), "a"))
    return _union(rows).groupBy("approach").agg(F.avg("a").alias("accuracy"), F.stddev_samp("a").alias("sd"))


def state_placement(spark: SparkSession, sf: str) -> DataFrame:
    """``budget, layout``: where the states of a graph would be kept under budgets of 0 and 100 MB."""
    g, _ = _ready(spark, sf, "transitions")
    states = _settled(g, model("gcn"))
    rows = []
    for mb in (0, 100):
        kept, layout = upkeep.placed(g, states, mb << 20)
        rows.append((mb, layout))
        for s in kept:
            s.state.unpersist()
            s.out.unpersist()
    return spark.createDataFrame(rows, "budget_mb int, layout string")


QUERIES = {f.__name__: f for f in (conditions_report, equivalence_report, custom_model, drift_audit, sweep_batch_size, sweep_queries, sweep_depth, sweep_eviction, sweep_chunk, guard_overhead, redundancy_by_batch, analytic_costs, trained_heads, state_placement, response_times, latency_bounds, constmsg_edges, phase_times)}
QUERIES |= {"delta_two_hop": two_hop_delta}
