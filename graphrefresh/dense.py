"""Layers of any width from loaded weights; their matrix products are taken a batch of vertices at a time."""

from __future__ import annotations

from collections.abc import Callable

from graphrefresh.functions.weights import Map, elu, guarded, leaky_relu, names, number, relu, weight
from graphrefresh.models import Layer, Model

Matrix = list[list[float]]


def _map(name: str, inputs: list[str], weights: Matrix) -> Map:
    return Map(name, tuple(inputs), tuple(tuple(float(x) for x in row) for row in weights))


def _relu_of(maps: Map) -> list[str]:
    return [relu(x) for x in maps.outputs]


def gcn(weights: dict[str, Matrix]) -> Layer:
    n = len(weights["w"][0])
    h, a, q, s = (names(c, n) for c in "haqs")
    w = _map("y", a, weights["w"])
    source = [f"(CASE WHEN deg > 0 THEN {x} / sqrt(deg) ELSE 0e0 END)" for x in h]
    return Layer(source, [*q, "1e0"], [guarded(x, f"sqrt(s{n})") for x in s], _relu_of(w), strip=[f"{x} * sqrt(s{n})" for x in a], reads_degree=True, update_maps=(w,))


def sage_mean(weights: dict[str, Matrix]) -> Layer:
    n = len(weights["w"][0])
    h, a, q, s = (names(c, n) for c in "haqs")
    w = _map("y", a, weights["w"])
    return Layer(h, [*q, "1e0"], [guarded(x, f"s{n}") for x in s], _relu_of(w), strip=[f"{x} * s{n}" for x in a], update_maps=(w,))


def gin(weights: dict[str, Matrix], eps: float = 0.5) -> Layer:
    n = len(weights["w"][0])
    h, a, q, s = (names(c, n) for c in "haqs")
    first = _map("y", [f"{number(1 + eps)} * {x} + {y}" for x, y in zip(h, a, strict=True)], weights["w"])
    second = _map("z", _relu_of(first), weights["w2"])
    return Layer(h, q, s, second.outputs, self_term=True, update_maps=(first, second))


def gat(weights: dict[str, Matrix]) -> Layer:
    """``w`` transforms; ``to`` and ``of`` are the attention vectors of the destination and the source, one row each."""
    n, m = len(weights["w"][0]), len(weights["w"])
    wide, q = _map("x", names("h", n), weights["w"]), names("q", m)
    score = f"exp({leaky_relu(f'(p0 + q{m})')})"
    finish = [guarded(x, f"s{m}") for x in names("s", m)]
    return Layer(
        [*wide.outputs, "u0"], [*[f"{score} * {x}" for x in q], score], finish, [elu(x) for x in names("a", m)], target=["v0"], strip=[f"{x} * s{m}" for x in names("a", m)],
        source_maps=(wide, _map("u", wide.outputs, weights["of"])), target_maps=(wide, _map("v", wide.outputs, weights["to"])),
    )


KINDS: dict[str, Callable[[dict[str, Matrix]], Layer]] = {"gcn": gcn, "sage_mean": sage_mean, "gin": gin, "gat": gat}


def dense_model(kind: str, layers: list[dict[str, Matrix]]) -> Model:
    """A model of a kind from the weights of its layers, whatever their widths."""
    return Model(f"dense_{kind}", tuple(KINDS[kind](w) for w in layers))


def drawn_weights(widths: list[int]) -> list[dict[str, Matrix]]:
    """Fixed binary fractions, small enough that wide sums keep their size: weights where no trained ones are at hand."""
    out = []
    for k, (n, m) in enumerate(zip(widths, widths[1:], strict=False), 1):
        small = lambda rows, cols, offset, k=k, n=n: [[weight(k, i, j, offset) * 8 / n for j in range(cols)] for i in range(rows)]
        out.append({"w": small(m, n, 0), "w2": small(m, m, 1), "to": small(1, m, 2), "of": small(1, m, 3)})
    return out
