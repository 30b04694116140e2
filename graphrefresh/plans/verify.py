"""Checks whether a layer may be refreshed incrementally, by trials that look for a counter-example."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphrefresh.models import RELATIONS, Layer, Model
from graphrefresh.plans import baselines
from graphrefresh.plans.delta import Refresh, refresh
from graphrefresh.plans.full import LayerState, forward, vector
from graphrefresh.sources.graphs import Batch, Graph, apply, expanded, features

CONDITIONS = ("context_mergeable", "sum_mergeable", "combine_distributes", "combine_invertible", "source_only")


@dataclass(frozen=True)
class Bound:
    """Trials and the relative difference that counts as a counter-example; sizes of the drawn graphs and batches."""

    trials: int = 2000
    tolerance: float = 1e-9
    seed: int = 7


def _drawn(spark: SparkSession, layer: Layer, bound: Bound) -> DataFrame:
    """``trial, x0.., y0..``: two partial states a trial, sixteenths, contexts (columns past the sums) positive."""
    def value(side: int, i: int):
        u = F.pmod(F.xxhash64("id", F.lit(bound.seed), F.lit(side), F.lit(i)), F.lit(64)) / 16.0
        return u + 0.0625 if i >= layer.sums else u - 2.0
    cols = [value(s, i).alias(f"{p}{i}") for s, p in enumerate("xy") for i in range(layer.state_width)]
    return spark.range(bound.trials).select(F.col("id").alias("trial"), *cols)


def stated(vectors: DataFrame, layer: Layer) -> DataFrame:
    """As ``_drawn``, from the rows of ``vectors`` (vec_id, embedding), a trial each: one state is a vector's first components, the other those that follow, round again where a vector ends; contexts are made positive."""
    def value(i: int):
        x = F.coalesce(F.get("embedding", F.pmod(F.lit(i), F.greatest(F.size("embedding"), F.lit(1)))).cast("double"), F.lit(0.0))
        return F.abs(x) + 0.0625 if i % layer.state_width >= layer.sums else x
    cols = [value(s * layer.state_width + i).alias(f"{p}{i}") for s, p in enumerate("xy") for i in range(layer.state_width)]
    return vectors.select(F.coalesce("vec_id", F.lit(-1)).cast("long").alias("trial"), *cols)


def _finished(layer: Layer, sums: list, contexts: list) -> list:
    """Column text of the finished aggregate with the given sums and contexts put in."""
    given = {f"s{i}": x for i, x in enumerate([*sums, *contexts])}
    out = []
    for text in layer.finish:
        for name, x in sorted(given.items(), key=lambda kv: -len(kv[0])):
            text = text.replace(name, f"({x})")
        out.append(text)
    return out


def _differs(left: list[str], right: list[str], tolerance: float) -> str:
    return " OR ".join(f"NOT coalesce(abs(({a}) - ({b})) <= {tolerance!r} * (1e0 + abs({a})), false)" for a, b in zip(left, right, strict=True))


def refutations(layer: Layer, tolerance: float) -> dict[str, str]:
    """By condition, the text that is true of a trial (x0.., y0..) that refutes it.

    Contexts and sums must merge from parts and take parts back (deletions are negative messages, so extremes fail);
    applying the context must distribute over the sum; it must be undone for every context, which asks for an inverse
    rather than for monotony; and messages must not read the destination, else its readers are summed anew.
    """
    n = range(layer.state_width)
    sums, ctx = list(range(layer.sums)), [i for i in n if i >= layer.sums]
    both = {"sum": lambda i: f"x{i} + y{i}", "max": lambda i: f"greatest(x{i}, y{i})", "min": lambda i: f"least(x{i}, y{i})"}[layer.combine_by]
    back = {"sum": lambda i: f"(x{i} + y{i}) - y{i}", "max": both, "min": both}[layer.combine_by]
    merged = lambda part: _differs([back(i) for i in part], [f"x{i}" for i in part], tolerance) if part else "false"
    z = [f"x{i}" for i in ctx]
    apart = [f"({a}) + ({b})" for a, b in zip(_finished(layer, [f"x{i}" for i in sums], z), _finished(layer, [f"y{i}" for i in sums], z), strict=True)]
    together = _finished(layer, [f"x{i} + y{i}" for i in sums], z)
    if layer.strip is None:
        undone = _differs(_finished(layer, [f"x{i}" for i in sums], z), [f"x{i}" for i in sums], tolerance)
    else:
        done = _finished(layer, [f"x{i}" for i in sums], z)
        strip = [text for text in layer.strip]
        for i in reversed(range(layer.sums)):
            strip = [t.replace(f"a{i}", f"({done[i]})") for t in strip]
        for i in reversed(ctx):
            strip = [t.replace(f"s{i}", f"x{i}") for t in strip]
        undone = _differs(strip, [f"x{i}" for i in sums], tolerance)
    if layer.per_relation and layer.strip is None and layer.contexts:
        undone = "false"  # relations are added up last and their sums are stored, so nothing is stripped
    return {"context_mergeable": merged(ctx), "sum_mergeable": merged(sums), "combine_distributes": _differs(apart, together, tolerance), "combine_invertible": undone, "source_only": "true" if layer.reads_target else "false"}


def conditions(spark: SparkSession, layer: Layer, bound: Bound = Bound(), vectors: DataFrame | None = None) -> DataFrame:
    """``condition, holds, counterexample``: the first trial that refutes a condition, null where none does. Trials are drawn, or are all rows of ``vectors``."""
    rows = _drawn(spark, layer, bound) if vectors is None else stated(vectors, layer)
    found = rows.agg(*[F.min(F.when(F.expr(t), F.col("trial"))).alias(c) for c, t in refutations(layer, bound.tolerance).items()])
    cells = F.explode(F.array(*[F.struct(F.lit(c).alias("condition"), F.col(c).isNull().alias("holds"), F.col(c).alias("counterexample")) for c in CONDITIONS]))
    return found.select(cells.alias("r")).select("r.*")


def may_refresh(spark: SparkSession, model: Model, bound: Bound = Bound()) -> bool:
    """Whether all layers meet the conditions; reading the destination is allowed, as those vertices are summed anew."""
    for layer in model.layers:
        if conditions(spark, layer, bound).where("NOT holds AND condition <> 'source_only'").limit(1).count():
            return False
    return True


def checked_refresh(old: Graph, states: list[LayerState], b: Batch, model: Model) -> tuple[Refresh, bool]:
    """A user's own model: incremental if it passes the check, else every affected vertex over all its in-edges."""
    spark = old.vertices.sparkSession
    if may_refresh(spark, model):
        return refresh(old, states, b, model), True
    fronts = baselines.reach(old, expanded(old, b), model)
    return baselines.cache_reuse(old, states, b, model, fronts), False


def custom(name: str, depth: int, **parts) -> Model:
    """A model of a user's own expressions; see Layer for the names that each part may read."""
    return Model(name, tuple(Layer(**parts) for _ in range(depth)))


def drawn_graph(spark: SparkSession, seed: int, vertices: int = 60, edges: int = 90) -> tuple[Graph, Batch]:
    """A small directed graph with sinks and a batch of each kind of change."""
    rng = np.random.default_rng(seed)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, vertices, (edges + 2, 2))})
    row = lambda a, b: (a, b, RELATIONS[(a + b) % 4], ((a + b) % 4 + 1) / 4)
    picked = rng.permutation(len(pairs))
    dele, ins, base = [pairs[i] for i in picked[:2]], [pairs[i] for i in picked[2:4]], [pairs[i] for i in [*picked[:2], *picked[4:]]]
    edge = "src long, dst long, rel string, w double"
    v = spark.range(vertices).select(F.col("id").alias("vid"), *features(F.col("id")))
    changed = v.where(F.col("vid") == int(rng.integers(vertices))).withColumn("h2", F.col("h2") + 0.5)
    make = lambda es: spark.createDataFrame([row(*e) for e in es], edge)
    return Graph(v, make(base)), Batch(make(ins), make(dele), changed, v.limit(0).select("vid"))


def equivalence(spark: SparkSession, model: Model, seeds: list[int], tolerance: float = 1e-9) -> DataFrame:
    """``model, seed, vertices, max_abs, equal``: incremental results against whole passes on drawn graphs."""
    out = None
    for seed in seeds:
        g, b = drawn_graph(spark, seed)
        got, want = refresh(g, forward(g, model, write=True), b, model).embeddings, forward(apply(g, expanded(g, b)), model)[-1].out
        h = vector(want)
        rows = want.select("vid", *[F.col(c).alias(f"o_{c}") for c in h]).join(got, "vid", "full")
        gap = F.greatest(*[F.coalesce(F.abs(F.col(c) - F.col(f"o_{c}")), F.lit(float("inf"))) for c in h])
        one = rows.agg(F.count(F.lit(1)).alias("vertices"), F.max(gap).alias("max_abs")).select(F.lit(model.name).alias("model"), F.lit(seed).alias("seed"), "vertices", "max_abs", (F.col("max_abs") <= tolerance).alias("equal"))
        out = one if out is None else out.unionByName(one)
    return out


def without_strip(layer: Layer) -> Layer:
    """The layer as one whose context can't be undone, for negative tests."""
    return replace(layer, strip=[f"0e0 * a{i}" for i in range(layer.sums)] if layer.strip else None)
