"""From a formula's parts to a layer: aggregators as sums with a context, so that they can be refreshed."""

from __future__ import annotations

from dataclasses import dataclass

from graphrefresh.functions.weights import guarded
from graphrefresh.models import ZOO, Layer, Model, model


@dataclass(frozen=True)
class Aggregator:
    """How an aggregator splits into what is summed, the context and its use; ``weigh`` is put round an edge's weight."""

    context: str
    weigh: str
    finish: str
    strip: str | None


#: Template names are the words in which formulas are written; {w} is the edge's weight or score.
AGGREGATORS = {
    "sum": Aggregator("", "{w}", "{s}", None),
    "mean": Aggregator("1e0", "{w}", "{s} / {z}", "{a} * {z}"),
    "weighted_mean": Aggregator("{w}", "{w}", "{s} / {z}", "{a} * {z}"),
    "softmax": Aggregator("exp({w})", "exp({w})", "{s} / {z}", "{a} * {z}"),
    "root_mean": Aggregator("1e0", "{w}", "{s} / sqrt({z})", "{a} * sqrt({z})"),
}

def decompose(aggregator: str, source: list[str], update: list[str], score: str = "1e0", target: list[str] | None = None, self_term: bool = False) -> Layer:
    """A layer whose neighbours' ``source`` vectors, weighed by ``score``, meet in the named aggregator."""
    sources, sums, shown = ([f"{p}{i}" for i in range(len(source))] for p in "qsa")
    if aggregator in ("max", "min"):
        return Layer(source, sources, sums, update, combine_by=aggregator, self_term=self_term)
    how = AGGREGATORS[aggregator]
    w, context = how.weigh.format(w=score), how.context.format(w=score)
    z = f"s{len(source)}"
    finish = [guarded(s, z) if how.finish == "{s} / {z}" else guarded(s, f"sqrt({z})") if context else s for s in sums]
    strip = None if how.strip is None else [how.strip.format(a=a, z=z) for a in shown]
    return Layer(source, [*[f"({w}) * {q}" for q in sources], *([context] if context else [])], finish, update, target=target or [], strip=strip, self_term=self_term)


def known(name: str, depth: int = 2) -> Model | None:
    """A model of the zoo by any of its usual spellings."""
    key = "".join(c for c in name.lower() if c.isalnum())
    same = {"".join(c for c in n if c.isalnum()): n for n in ZOO} | {"graphsage": "sage_mean", "graphsagemean": "sage_mean", "graphattention": "gat", "graphconvolution": "gcn", "graphisomorphism": "gin"}
    return model(same[key], depth) if key in same else None
