"""The model zoo: a layer is five groups of column expressions and the flags that decide how it may be refreshed."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from graphrefresh.functions.weights import Map, dot, elu, guarded, leaky_relu, linear, matvec, names, norm, number, relu, sigmoid, weight

#: Width of the zoo's layers; `dense` makes layers of any width from loaded weights.
WIDTH = 4
#: Relations of the typed graph.
RELATIONS = ("contains", "in_order", "placed", "placed_by")


@dataclass(frozen=True)
class Layer:
    """One layer over h0.. of the layer below; widths are the lengths of its lists.

    ``source`` and ``target`` are hoisted per vertex (named q0.. and p0..; ``source`` may read the in-degree ``deg``);
    ``message`` is evaluated per edge over q, p, w and rel and summed (or, for ``combine_by`` min and max, folded) per
    destination to s0.., the state: first as many sums as ``finish`` has parts, then contexts; ``finish`` turns the state
    into a0.., where the context is applied, ``strip`` turns a and the contexts back; ``update`` reads h and a. Before
    source, target and update their matrix products (``*_maps``), which name further columns, are taken per vertex.
    """

    source: list[str]
    message: list[str]
    finish: list[str]
    update: list[str]
    target: list[str] = field(default_factory=list)
    strip: list[str] | None = None
    reads_degree: bool = False
    self_term: bool = False
    per_relation: bool = False
    combine_by: str = "sum"
    source_maps: tuple[Map, ...] = ()
    target_maps: tuple[Map, ...] = ()
    update_maps: tuple[Map, ...] = ()

    @property
    def reads_target(self) -> bool:
        return bool(self.target)

    @property
    def state_width(self) -> int:
        return len(self.message)

    @property
    def sums(self) -> int:
        return len(self.finish)

    @property
    def contexts(self) -> int:
        return len(self.message) - len(self.finish)


@dataclass(frozen=True)
class Model:
    name: str
    layers: tuple[Layer, ...]

    @property
    def reads_target(self) -> bool:
        return any(x.reads_target for x in self.layers)

    @property
    def constant_messages(self) -> bool:
        """Whether a message depends on nothing but its source, so that systems for such models could refresh it."""
        return not any(x.reads_target or x.reads_degree or x.contexts for x in self.layers)


H, A, Q, P, S = (names(c, WIDTH) for c in "haqps")


def _out(layer: int, offset: int = 0) -> list[str]:
    return [relu(x) for x in matvec(layer, A, WIDTH, offset)]


def _mean(layer: int, update: list[str], source: list[str] | None = None, message: list[str] | None = None, **flags) -> Layer:
    return Layer(source or H, [*(message or Q), "1e0"], [guarded(s, "s4") for s in S], update, strip=[f"{a} * s4" for a in A], **flags)


def gcn(k: int) -> Layer:
    source = [f"(CASE WHEN deg > 0 THEN {h} / sqrt(deg) ELSE 0e0 END)" for h in H]
    return Layer(source, [*Q, "1e0"], [guarded(s, "sqrt(s4)") for s in S], _out(k), strip=[f"{a} * sqrt(s4)" for a in A], reads_degree=True)


def sage_mean(k: int, self_concat: bool = False) -> Layer:
    update = [relu(linear(k, i, [*H, *A])) for i in range(WIDTH)] if self_concat else _out(k)
    return _mean(k, update, self_term=self_concat)


def sage_sum(k: int) -> Layer:
    return Layer(H, Q, S, _out(k))


def graph_conv(k: int) -> Layer:
    return Layer(H, [f"w * {q}" for q in Q], S, _out(k))


def gin(k: int, eps: float = 0.5) -> Layer:
    x = [f"({number(1 + eps)} * {h} + {a})" for h, a in zip(H, A, strict=True)]
    hidden = [relu(y) for y in matvec(k, x, WIDTH)]
    return Layer(H, Q, S, [dot([number(weight(k, i, j, 1)) for j in range(WIDTH)], hidden) for i in range(WIDTH)], self_term=True)


def comm_net(k: int) -> Layer:
    return Layer(H, Q, S, [f"{linear(k, i, H)} + {linear(k, i, A, 1)}" for i in range(WIDTH)], self_term=True)


def monet(k: int, sign: float = -1.0) -> Layer:
    """Gaussian kernels of the source; ``sign`` 1 has the exponent positive, which overflows on wide vectors."""
    def kernel(j: int) -> str:
        return f"exp({number(sign / 2)} * (" + " + ".join(f"({h} - {number(weight(k, j, d))}) * ({h} - {number(weight(k, j, d))}) * 0.125e0" for d, h in enumerate(H)) + "))"
    return Layer([kernel(j) for j in range(WIDTH)], Q, S, _out(k))


def pin_sage(k: int) -> Layer:
    source = [relu(f"{linear(k, i, H, 2)} + {number(weight(k, i, 5))}") for i in range(WIDTH)]
    return _mean(k, [relu(linear(k, i, [*H, *A])) for i in range(WIDTH)], source, [f"w * {q}" for q in Q], self_term=True)


def _by_relation(k: int, i: int, xs: list[str]) -> str:
    return "(CASE rel " + " ".join(f"WHEN '{r}' THEN {linear(k, i, xs, 3 + n)}" for n, r in enumerate(RELATIONS)) + " ELSE 0e0 END)"


def rgcn(k: int, per_relation: bool = False) -> Layer:
    """The context counts in-edges, of the vertex or of each of its relations."""
    update = [relu(f"{linear(k, i, H)} + a{i}") for i in range(WIDTH)]
    return _mean(k, update, H, [_by_relation(k, i, Q) for i in range(WIDTH)], self_term=True, per_relation=per_relation)


def gat(k: int) -> Layer:
    wh = matvec(k, H, WIDTH)
    score = f"exp({leaky_relu('(p0 + q4)')})"
    source = [*wh, linear(k, 7, wh, 1)]
    return Layer(source, [*[f"{score} * {q}" for q in Q], score], [guarded(s, "s4") for s in S], [elu(a) for a in A], target=[linear(k, 8, wh, 2)], strip=[f"{a} * s4" for a in A])


def rgat(k: int) -> Layer:
    """Weights, scores and sums by relation; relations are added up last."""
    wq, wp = [_by_relation(k, i, Q) for i in range(WIDTH)], [_by_relation(k, i, P) for i in range(WIDTH)]
    score = f"exp({leaky_relu(f'({linear(k, 7, wq, 1)} + {linear(k, 8, wp, 2)})')})"
    return Layer(H, [*[f"{score} * {x}" for x in wq], score], [guarded(s, "s4") for s in S], [elu(a) for a in A], target=H, per_relation=True)


def g_gcn(k: int) -> Layer:
    gate = [sigmoid(f"q{WIDTH + i} + p{i}") for i in range(WIDTH)]
    return Layer([*H, *matvec(k, H, WIDTH, 1)], [f"{g} * {q}" for g, q in zip(gate, Q, strict=True)], S, _out(k), target=matvec(k, H, WIDTH, 2))


def agnn(k: int) -> Layer:
    cosine = f"(CASE WHEN q4 * p4 > 0e0 THEN {dot(Q, P)} / (q4 * p4) ELSE 0e0 END)"
    return Layer([*H, norm(H)], [f"w * {cosine} * {q}" for q in Q], S, _out(k), target=[*H, norm(H)])


def sage_max(k: int) -> Layer:
    return Layer(H, Q, S, _out(k), combine_by="max")


def sage_min(k: int) -> Layer:
    return Layer(H, Q, S, _out(k), combine_by="min")


ZOO: dict[str, Callable[[int], Layer]] = {
    "monet": monet, "commnet": comm_net, "gcn": gcn, "sage_mean": sage_mean, "pinsage": pin_sage, "rgcn": rgcn, "gat": gat, "ggcn": g_gcn, "agnn": agnn, "rgat": rgat,
    "gin": gin, "sage_sum": sage_sum, "graphconv": graph_conv, "sage_max": sage_max, "sage_min": sage_min,
    "rgcn_relation": lambda k: rgcn(k, True), "sage_concat": lambda k: sage_mean(k, True),
}


def model(name: str, depth: int = 2) -> Model:
    """A model of the catalogue with fixed weights."""
    return Model(name, tuple(ZOO[name](k) for k in range(1, depth + 1)))
