"""Fixed model weights and the text of vector expressions over scalar columns.

Vectors of the exact path are scalar columns (h0, h1, ...), so that every step stays inside generated code. Expressions
are SQL text: Spark compiles them, and tests hand the same formulas to another engine.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Map:
    """A matrix product per vertex: column ``name``i is row i of ``weights`` times the expressions ``inputs``."""

    name: str
    inputs: tuple[str, ...]
    weights: tuple[tuple[float, ...], ...]

    @property
    def outputs(self) -> list[str]:
        return [f"{self.name}{i}" for i in range(len(self.weights))]


def mapped(rows: DataFrame, maps: Iterable[Map]) -> DataFrame:
    """``rows`` with the columns of all maps. A batch of vertices is one matrix product; only wide layers come here."""
    for m in maps:
        weights = np.asarray(m.weights, "f8").T

        def multiply(batches: Iterable[pa.RecordBatch], weights=weights) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x = np.asarray(b.column(b.num_columns - 1).flatten(), "f8").reshape(b.num_rows, len(weights))
                y = pa.FixedSizeListArray.from_arrays(pa.array((x @ weights).ravel()), weights.shape[1]).cast(pa.list_(pa.float64()))
                yield pa.RecordBatch.from_arrays([*b.columns[:-1], y], [*b.schema.names[:-1], "_y"])

        own = rows.columns
        given = rows.select(*own, F.array(*[F.expr(x) for x in m.inputs]).alias("_x"))
        out = given.mapInArrow(multiply, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema] + ["_y array<double>"]))
        rows = out.select(*own, *[F.col("_y")[i].alias(c) for i, c in enumerate(m.outputs)])
    return rows


def number(x: float) -> str:
    """A double literal in any SQL dialect."""
    return f"{x!r}e0" if "e" not in repr(x) else repr(x)


def weight(layer: int, i: int, j: int, offset: int = 0) -> float:
    """A dyadic weight, so that sums of products are exact in any order."""
    return (((31 * i + 17 * j + 7 * layer + 3 + 5 * offset) % 11) - 5) / 8


def linear(layer: int, row: int, names: list[str], offset: int = 0) -> str:
    return "(" + " + ".join(f"{number(weight(layer, row, j, offset))} * {n}" for j, n in enumerate(names)) + ")"


def matvec(layer: int, names: list[str], width: int, offset: int = 0) -> list[str]:
    return [linear(layer, i, names, offset) for i in range(width)]


def names(prefix: str, width: int) -> list[str]:
    return [f"{prefix}{i}" for i in range(width)]


def relu(x: str) -> str:
    return f"greatest({x}, 0e0)"


def leaky_relu(x: str, slope: float = 0.2) -> str:
    return f"(CASE WHEN {x} > 0e0 THEN {x} ELSE {number(slope)} * {x} END)"


def elu(x: str) -> str:
    return f"(CASE WHEN {x} > 0e0 THEN {x} ELSE exp({x}) - 1e0 END)"


def sigmoid(x: str) -> str:
    return f"(1e0 / (1e0 + exp(-({x}))))"


def tanh(x: str) -> str:
    return f"tanh({x})"


def dot(a: list[str], b: list[str]) -> str:
    return "(" + " + ".join(f"{x} * {y}" for x, y in zip(a, b, strict=True)) + ")"


def norm(a: list[str]) -> str:
    return f"sqrt({dot(a, a)})"


def guarded(top: str, bottom: str) -> str:
    """0 where the context is 0, as for a vertex without in-edges."""
    return f"(CASE WHEN {bottom} = 0e0 THEN 0e0 ELSE ({top}) / (CASE WHEN {bottom} = 0e0 THEN 1e0 ELSE {bottom} END) END)"
