"""Quality classifier: a cumulative-link model over hashed words gives expected grades and tail probabilities."""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.llm.common import text_or_empty

#: Weights shared by all thresholds; words fall on them by crc32.
N_WEIGHTS = 1 << 20
#: The fit takes at most this many rated documents, those with the smallest md5 of their id.
MAX_RATED = 20_000
EPOCHS, RATE, PENALTY, BATCH = 30, 0.05, 1e-3, 256
#: A slot gets a weight when this share of the rated documents, and this number of them, have it: rarer words would only be learnt by heart.
MIN_SHARE, MIN_RATED = 0.002, 3
#: A document is selected when its grade is probably above the lowest.
TAIL, MIN_TAIL = 2, 0.45


@dataclass
class CumulativeLink:
    """P(grade > k) = sigmoid(score - thresholds[k]), thresholds in ascending order; grades are 0 to len(thresholds)."""

    weights: np.ndarray
    thresholds: np.ndarray

    def tails(self, scores: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(scores[:, None] - self.thresholds, -30, 30)))


def features(text: str) -> np.ndarray:
    """Slots of the distinct words of a whole text, in lower case and without stops at their ends."""
    return np.fromiter({zlib.crc32(w.encode("utf-8", "surrogatepass")) % N_WEIGHTS for w in {x.strip(".,;:!?") for x in set(text.lower().split())}}, np.int64)


def _offsets(xs: list[np.ndarray]) -> np.ndarray:
    return np.repeat(np.arange(len(xs)), [len(x) for x in xs])


def _scores(weights: np.ndarray, slots: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(rows, weights[slots], n)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def slopes(scores: np.ndarray, thresholds: np.ndarray, grades: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each document's negative log likelihood, the derivative by its score and by the thresholds (one column each)."""
    edge, each = np.concatenate([[-np.inf], thresholds, [np.inf]]), np.arange(len(scores))
    high, low = sigmoid(edge[grades + 1] - scores), sigmoid(edge[grades] - scores)
    p = np.maximum(high - low, 1e-9)
    up, down = high * (1 - high) / p, low * (1 - low) / p
    by_edge = np.zeros((len(scores), len(edge)))
    by_edge[each, grades + 1] -= up
    by_edge[each, grades] += down
    return up - down, by_edge[:, 1:-1]


def loss(scores: np.ndarray, thresholds: np.ndarray, grades: np.ndarray) -> float:
    """Mean negative log likelihood."""
    edge = np.concatenate([[-np.inf], thresholds, [np.inf]])
    return float(-np.log(np.maximum(sigmoid(edge[grades + 1] - scores) - sigmoid(edge[grades] - scores), 1e-9)).mean())


def fit(xs: list[np.ndarray], grades: np.ndarray, n_grades: int | None = None, seed: int = 7) -> CumulativeLink:
    """Maximum likelihood by AdaGrad. Thresholds are a first one and positive steps, so they stay in order."""
    k = int(n_grades or (grades.max() + 1 if len(grades) else 2))
    w, g2 = np.zeros(N_WEIGHTS), np.full(N_WEIGHTS, 1e-8)
    often = np.bincount(np.concatenate(xs), minlength=N_WEIGHTS) >= max(MIN_RATED, MIN_SHARE * len(xs)) if len(xs) else w > 0
    xs = [x[often[x]] for x in xs]
    share = np.clip(np.array([(grades > j).mean() if len(grades) else 0.5 for j in range(k - 1)]), 1e-3, 1 - 1e-3)
    cuts = -np.log(share / (1 - share))
    raw = np.concatenate([cuts[:1], np.log(np.maximum(np.diff(cuts), 0.05))])
    raw2, rng = np.full(len(raw), 1e-8), np.random.default_rng(seed)
    unroll = lambda r: np.concatenate([r[:1], r[0] + np.cumsum(np.exp(r[1:]))])
    for _ in range(EPOCHS if len(xs) else 0):
        order = rng.permutation(len(xs))
        for i in range(0, len(order), BATCH):
            part = order[i : i + BATCH]
            x, y = [xs[j] for j in part], grades[part]
            slots, rows = np.concatenate(x), _offsets(x)
            by_score, by_threshold = slopes(_scores(w, slots, rows, len(x)), unroll(raw), y)
            grad = np.bincount(slots, by_score[rows], N_WEIGHTS) / len(x)
            hit = np.unique(slots)
            grad[hit] += PENALTY * w[hit]
            g2[hit] += grad[hit] ** 2
            w[hit] -= RATE * grad[hit] / np.sqrt(g2[hit])
            dth = by_threshold.sum(axis=0) / len(x)
            draw = np.concatenate([[dth.sum()], [dth[j:].sum() * np.exp(raw[j]) for j in range(1, k - 1)]])
            raw2 += draw**2
            raw -= RATE * draw / np.sqrt(raw2)
    return CumulativeLink(w, unroll(raw))


def graded(labels: DataFrame) -> DataFrame:
    """``doc_id, grade``: 0 toxic, 1 not toxic and of low quality, 2 not toxic and good; the lowest where a document is rated more than once. Rows without an id or a rating are left out."""
    rows = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL AND toxic IS NOT NULL")
    return rows.groupBy("doc_id").agg(F.min(F.expr("CASE WHEN toxic > 0 THEN 0 WHEN quality > 0 THEN 2 ELSE 1 END")).alias("grade"))


def train(docs: DataFrame, grades: DataFrame, max_rated: int = MAX_RATED) -> CumulativeLink:
    """Fit on at most ``max_rated`` rated documents; their distinct word slots, not their texts, come to the driver.

    Of rows that share a rated id one counts, so there are never more rows than rated ids. A null or empty text is a
    document without words; documents without a grade, and grades without a document, play no part; without any rated
    document the model gives every text the same grade.
    """
    rated = grades.select("doc_id", "grade").orderBy(F.md5(F.col("doc_id").cast("string"))).limit(max_rated)
    rows = docs.select("doc_id", text_or_empty().alias("text")).join(rated, "doc_id").select("doc_id", "text", "grade")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            slots = [features(t).astype("<i4").tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(slots, pa.binary()), b.column(2).cast(pa.int64())], ["doc_id", "slots", "grade"])

    one = rows.mapInArrow(run, "doc_id long, slots binary, grade long").groupBy("doc_id").agg(F.min(F.struct("slots", "grade")).alias("x"))
    got = one.select("doc_id", "x.slots", "x.grade").toArrow().sort_by("doc_id")
    xs = [np.frombuffer(x, "<i4").astype(np.int64) for x in got.column("slots").to_pylist()]
    return fit(xs, np.array(got.column("grade").to_pylist(), np.int64), 3)


def grade(docs: DataFrame, model: CumulativeLink, tail: int = TAIL, min_tail: float = MIN_TAIL) -> DataFrame:
    """``doc_id, expected_grade, p_ge_1 .. p_ge_k, kept`` of every row of ``docs`` (doc_id, text), from its whole text.

    ``kept`` says whether P(grade >= ``tail``) is at least ``min_tail``. A null or empty text has no words and gets the
    model's prior; null and repeated ids are scored like any other row; extra columns are ignored; no rows give no rows.
    Only words with a weight are looked up, and the model is as large as its slots, whatever the number of documents.
    """
    k = len(model.thresholds)
    bc = docs.sparkSession.sparkContext.broadcast((model.weights.astype("f8"), model.thresholds))
    schema = "doc_id long, expected_grade double, " + ", ".join(f"p_ge_{j + 1} double" for j in range(k)) + ", kept boolean"

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = CumulativeLink(*bc.value)
        for b in batches:
            for i in range(0, b.num_rows, 500):
                part = b.slice(i, 500)
                xs = [features(t) for t in part.column(1).to_pylist()]
                s = _scores(m.weights, np.concatenate(xs) if xs else np.zeros(0, np.int64), _offsets(xs).astype(np.int64), len(xs))
                p = m.tails(s)
                cols = [part.column(0), pa.array(p.sum(1)), *[pa.array(p[:, j]) for j in range(k)], pa.array(p[:, tail - 1] >= min_tail)]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "expected_grade", *[f"p_ge_{j + 1}" for j in range(k)], "kept"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).mapInArrow(run, schema)
