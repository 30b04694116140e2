"""LM scoring by Katz backoff: Good-Turing discounted bigrams, exactly normalised backoff weights, unigrams, one unknown word.

Texts become blocks of a few million tokens, each with its own vocabulary. A block asks the count tables, which are dealt
out by word and by history, about each of its distinct words and pairs once, in one message to each task that has any; what comes back
is all that its texts need. A block sends no more messages than it has distinct words or pairs, so their number grows with
the corpus, not with its square. So neither the model nor the texts are ever in one place, and a token costs a few bytes.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphrefresh.llm.common import shuffle_partitions, text_or_empty, written
from graphrefresh.llm.near_dup import mix

#: Counts up to K are discounted.
K = 5
#: Tokens of a block; tokens for each task of the count tables.
BLOCK, SHARE = 1_500_000, 2_000_000
#: At most as many histories are hot, whose followers are dealt out by pair and whose sums (some 60 bytes each) are broadcast.
HOT = 16_384
BLOCKS_A_TASK = 2
#: Hash of the end token; ids of an unknown word and of the place before a text.
END, UNKNOWN, START = 0xE4D0_0000_0000_0001, -1, -2


def pack(a: np.ndarray) -> bytes:
    """Integers, byte by byte of all, compressed: small numbers cost about a byte or less."""
    import zstandard

    a = np.asarray(a)
    kind = "<i8" if len(a) and (a.max() >= 1 << 31 or a.min() < -(1 << 31)) else "<i4"
    return kind[1:].encode() + zstandard.ZstdCompressor(level=1).compress(a.astype(kind).view(np.uint8).reshape(-1, int(kind[2])).T.tobytes())


def unpack(b: bytes) -> np.ndarray:
    import zstandard

    kind = "<" + b[:2].decode()
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(b[2:], max_output_size=1 << 31), np.uint8) if len(b) > 2 else np.zeros(0, np.uint8)
    return np.ascontiguousarray(raw.reshape(int(kind[2]), -1).T).view(kind).ravel().astype(np.int64)


def discounts(n: np.ndarray) -> np.ndarray:
    """Factors of counts 0 to K from n[r], the number of events seen r times (r up to K + 1), by Good-Turing with Katz's cut-off.

    Where these are not between 0 and 1, as for small or odd tables, half a count is taken off each.
    """
    r = np.arange(1, K + 1)
    with np.errstate(all="ignore"):
        cut = (K + 1) * n[K + 1] / n[1]
        d = ((r + 1) * n[r + 1] / (r * n[r]) - cut) / (1 - cut)
    if not (np.isfinite(d).all() and (d > 0).all() and (d < 1).all()):
        d = (r - 0.5) / r
    return np.concatenate([[0.0], d])


def discounted(count: np.ndarray, d: np.ndarray) -> np.ndarray:
    return count * np.where(count > K, 1.0, d[np.minimum(count, K)])


class Unigrams:
    """P(word): discounted counts; all that is left goes to the unknown word, so that they add up to 1."""

    def __init__(self, n: np.ndarray, kept_big: float, total: float):
        self.n, self.d, self.total = n, discounts(n), total
        mass = (discounted(np.arange(K + 1), self.d) * n[: K + 1]).sum() + kept_big if total else 0.0
        # without a count to take from, the unknown word gets one more token's share
        self.over = total if mass < total else total + 1
        self.left = 1 - mass / self.over if total else 1.0

    def p(self, count: np.ndarray) -> np.ndarray:
        return np.where(count > 0, discounted(count, self.d) / max(self.over, 1), self.left)


def backoff(total: np.ndarray, n: np.ndarray, big: np.ndarray, lower: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(alpha, over) of histories: seen words have their discounted count over ``over``, others alpha times their lower-order probability, and all add up to 1.

    ``over`` is the history's count, or one more where no count was discounted and nothing would be left. The unknown word
    is never seen, so there always are others.
    """
    seen = (n * discounted(np.arange(1, K + 1), d)).sum(axis=1) + big
    over = np.where(seen < total, total, total + 1)
    return (1 - seen / over) / (1 - lower), over


def _held_in(doc_id: Column) -> Column:
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(7)) != 2


_BLOCK_SCHEMA = "block long, doc_ids array<long>, train binary, lens binary, vocab binary, tokens binary"


def blocks(docs: DataFrame) -> DataFrame:
    """Tokens of whole texts, lower-cased in A-Z and ended by the end token, as places in a block's sorted vocabulary of hashes."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        class Hashes(dict):
            def __missing__(self, word: bytes) -> int:
                self[word] = h = xxhash.xxh64_intdigest(word)
                return h

        known, number = Hashes(), TaskContext.get().partitionId() << 24
        ids, train, hashes = [], [], []

        def flush() -> pa.RecordBatch:
            nonlocal number
            number += 1
            vocab, tokens = np.unique(np.concatenate(hashes), return_inverse=True)
            row = [[number - 1], [ids[:]], [np.array(train, "u1").tobytes()], [pack(np.array([len(h) for h in hashes]))], [vocab.astype("<u8").tobytes()], [pack(tokens)]]
            out = pa.RecordBatch.from_arrays([pa.array(row[0], pa.int64()), pa.array(row[1], pa.list_(pa.int64())), *[pa.array(r, pa.binary()) for r in row[2:]]], ["block", "doc_ids", "train", "lens", "vocab", "tokens"])
            for x in (ids, train, hashes):
                x.clear()
            if len(known) > 500_000:
                known.clear()
            return out

        size = 0
        for b in batches:
            for doc, text, held_in in zip(*[b.column(i).to_pylist() for i in range(3)], strict=True):
                words = text.encode("utf-8", "surrogatepass").lower().split()
                h = np.empty(len(words) + 1, np.uint64)
                h[:-1] = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
                h[-1] = END
                ids.append(doc)
                train.append(held_in)
                hashes.append(h)
                size += len(h)
                if size >= BLOCK:
                    yield flush()
                    size = 0
        if hashes:
            yield flush()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"), _held_in(F.col("doc_id")).alias("train")).mapInArrow(run, _BLOCK_SCHEMA)


class Block:
    """A block's arrays, and what the count tables said of them."""

    def __init__(self, row: dict):
        self.vocab = np.frombuffer(row["vocab"], "<u8")
        self.tokens, self.lens = unpack(row["tokens"]), unpack(row["lens"])
        self.doc = np.repeat(np.arange(len(self.lens)), self.lens)
        self.train = np.frombuffer(row["train"], "u1")[self.doc].astype(bool)

    def word_request(self, parts: int) -> Iterator[tuple[int, bytes, bytes]]:
        counts = np.bincount(self.tokens[self.train], minlength=len(self.vocab))
        cuts = np.searchsorted(self.vocab, np.arange(1, parts, dtype=np.uint64) * np.uint64((1 << 64) // parts))
        for part, (a, z) in enumerate(zip([0, *cuts], [*cuts, len(self.vocab)], strict=True)):
            if z > a:
                yield part, self.vocab[a:z].tobytes(), pack(counts[a:z])

    def words(self, answers: list[dict]) -> None:
        """Counts and ids of the vocabulary, from the answers of all word tasks."""
        answers = sorted(answers, key=lambda r: r["part"])
        self.count = np.concatenate([unpack(r["a"]) for r in answers])
        self.id = np.concatenate([unpack(r["b"]) for r in answers])

    def pairs(self, texts: int, hot: float, parts: int) -> None:
        """Distinct pairs with a known history, in the order of the requests."""
        nv = len(self.vocab)
        before = np.empty_like(self.tokens)
        before[1:] = self.tokens[:-1]
        before[np.concatenate([[0], np.cumsum(self.lens)[:-1]])] = nv
        pair, self.pair_of = np.unique(before * nv + self.tokens, return_inverse=True)
        h, w = pair // nv, pair % nv
        hid, hcount = np.append(self.id, START)[h], np.append(self.count, texts)[h]
        wid = self.id[w]
        is_hot = hcount > hot
        with np.errstate(over="ignore"):
            key = mix(hid.astype(np.uint64))
            key = np.where(is_hot, mix(key + wid.astype(np.uint64)), key)
        part = (key % np.uint64(parts)).astype(np.int64)
        order = np.lexsort((w, wid, hid, is_hot, part))
        self.order = order[hcount[order] > 0]
        self.h, self.w, self.hid, self.wid, self.hcount, self.hot, self.part = h, w, hid, wid, hcount, is_hot, part

    def pair_request(self, p1: np.ndarray) -> Iterator[tuple]:
        counts = np.bincount(self.pair_of[self.train], minlength=len(self.h))
        o = self.order
        edge = np.flatnonzero(np.diff(self.part[o] * 2 + self.hot[o])) + 1
        for x in np.split(o, edge):
            if len(x):
                values, place = np.unique(p1[self.w[x]], return_inverse=True)
                yield int(self.part[x[0]]), bool(self.hot[x[0]]), pack(self.hid[x]), pack(self.wid[x]), pack(counts[x]), values.tobytes(), pack(place)


_ANSWER = "block long, part int, hot boolean, a binary, b binary, c binary"
_NAMES = ["block", "part", "hot", "a", "b", "c"]


def _table(rows: list[tuple]) -> pa.Table:
    kinds = [pa.int64(), pa.int32(), pa.bool_(), pa.binary(), pa.binary(), pa.binary()]
    return pa.table({n: pa.array([r[i] for r in rows], k) for i, (n, k) in enumerate(zip(_NAMES, kinds, strict=True))})


def _tally(counts: np.ndarray) -> np.ndarray:
    """How many counts are 0, 1 .. K + 1; the sum of those over K; the sum of all; how many there are."""
    return np.concatenate([np.bincount(counts[counts <= K + 1], minlength=K + 2), [counts[counts > K].sum(), counts.sum(), len(counts)]]).astype("<i8")


def _word_task(parts: int):
    """Add up a task's words; rare words get the larger ids. A row for block -1 has the task's tally."""

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.to_pylist()
        keys, counts = [np.frombuffer(r["a"], "<u8") for r in rows], [unpack(r["b"]) for r in rows]
        _, place = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.bincount(place, np.concatenate(counts)).astype(np.int64)
        ids = np.empty_like(total)
        ids[np.argsort(-total, kind="stable")] = np.arange(len(total)) * parts + rows[0]["part"]
        ids[total == 0] = UNKNOWN
        out, at = [(-1, rows[0]["part"], False, _tally(total[total > 0]).tobytes(), None, None)], 0
        for r, k in zip(rows, keys, strict=True):
            own = place[at : at + len(k)]
            at += len(k)
            out.append((r["block"], r["part"], False, pack(total[own]), pack(ids[own]), None))
        return _table(out)

    return run


def _pair_task(rows: pa.Table) -> pa.Table:
    """Add up a task's pairs and, for each history, what its backoff weight needs.

    Rows for block -1 have the task's tally; those for block -2 its part of the hot histories' sums.
    """
    rows = rows.to_pylist()
    h, w, c = ([unpack(r[k]) for r in rows] for k in "abc")
    p = [np.frombuffer(r["d"], "<f8")[unpack(r["e"])] for r in rows]
    sizes = [len(x) for x in h]
    hot = np.repeat([r["hot"] for r in rows], sizes)
    h, w, c, p = (np.concatenate(x) for x in (h, w, c, p))
    order = np.lexsort((w, h))
    new = np.concatenate([[True], (np.diff(h[order]) != 0) | (np.diff(w[order]) != 0)])
    pair = np.empty(len(h), np.int64)
    pair[order] = np.cumsum(new) - 1
    total = np.bincount(pair, c).astype(np.int64)
    first = order[new]
    history, place = np.unique(h[first], return_inverse=True)
    seen = total > 0
    n = np.stack([np.bincount(place[total == r], minlength=len(history)) for r in range(1, K + 1)], axis=1)
    big = np.bincount(place, np.where(total > K, total, 0), len(history)).astype(np.int64)
    lower = np.bincount(place[seen], p[first][seen], len(history))
    out = [(-1, 0, False, _tally(total[seen]).tobytes(), None, None)]
    if hot.any():
        own = np.unique(np.searchsorted(history, h[hot]))
        out.append((-2, 0, True, pack(history[own]), pack(np.column_stack([n[own], big[own]]).ravel()), lower[own].tobytes()))
    at = 0
    for r, size in zip(rows, sizes, strict=True):
        mine = slice(at, at + size)
        at += size
        sums = lows = None
        if not r["hot"]:
            own = np.searchsorted(history, np.unique(h[mine]))
            sums, lows = pack(np.column_stack([n[own], big[own]]).ravel()), lower[own].tobytes()
        out.append((r["block"], r["part"], r["hot"], pack(total[pair[mine]]), sums, lows))
    return _table(out)


def _sum_tallies(answers: DataFrame) -> np.ndarray:
    """The tasks' tallies, summed up: a few numbers come to the driver."""
    size = K + 5

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            total = sum((np.frombuffer(x, "<i8") for x in b.column(0).to_pylist()), np.zeros(size, np.int64))
            yield pa.RecordBatch.from_arrays([pa.array([int(x)], pa.int64()) for x in total], [f"x{i}" for i in range(size)])

    rows = answers.where("block = -1").select("a").mapInArrow(run, ", ".join(f"x{i} long" for i in range(size)))
    return np.array([x or 0 for x in rows.agg(*[F.sum(f"x{i}") for i in range(size)]).first()], np.int64)


def _hot_sums(answers: DataFrame) -> dict[int, tuple]:
    """Sums of the hot histories, HOT at most: each has more than that part of all tokens."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for x, y, z in zip(*[b.column(i).to_pylist() for i in range(3)], strict=True):
                n = unpack(y).reshape(-1, K + 1)
                yield pa.RecordBatch.from_arrays([pa.array(unpack(x)), *[pa.array(n[:, i]) for i in range(K + 1)], pa.array(np.frombuffer(z, "<f8"))], ["h", *[f"n{i}" for i in range(K + 1)], "low"])

    rows = answers.where("block = -2").select("a", "b", "c").mapInArrow(run, "h long, " + ", ".join(f"n{i} long" for i in range(K + 1)) + ", low double")
    rows = rows.groupBy("h").agg(*[F.sum(f"n{i}").alias(f"n{i}") for i in range(K + 1)], F.sum("low").alias("low")).collect()
    return {r[0]: (tuple(r[1 : K + 2]), r[K + 2]) for r in rows}


def score(docs: DataFrame, block_share: int = SHARE) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score`` of every row of ``docs`` (doc_id, text).

    The model learns from the rows for which crc32 of the doc_id's digits modulo 7 is not 2. ``score`` is the sum of
    log10 P(token | token before) over the words and the end token, ``base_score`` that of add-one unigrams. A pair that
    was seen has its discounted relative frequency; another has its history's backoff weight times the word's own
    probability; after an unseen history the latter alone counts. Words that training lacks are one unknown word.

    A null text is an empty one and has an end token; a null doc_id counts as an id without digits, which is trained on;
    repeated rows count each time; extra columns are ignored; no rows give no rows.
    """
    spark = docs.sparkSession
    base = written(blocks(docs), "blocks")

    def ask_words(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                rows = [(row["block"], p, False, k, c, None) for p, k, c in Block(row).word_request(parts)]
                yield from _table(rows).to_batches()

    def measure(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lens, train = [unpack(x) for x in b.column(0).to_pylist()], [np.frombuffer(x, "u1") for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([int(x.sum()) for x in lens]), pa.array([int(x.sum()) for x in train])], ["tokens", "texts"])

    tokens, texts = (x or 0 for x in base.select("lens", "train").mapInArrow(measure, "tokens long, texts long").agg(F.sum("tokens"), F.sum("texts")).first())
    parts = max(shuffle_partitions(spark), -(-tokens // block_share))
    words = written(base.mapInArrow(ask_words, _ANSWER).repartition(parts, "part").groupBy("part").applyInArrow(_word_task(parts), _ANSWER), "words")
    t = _sum_tallies(words)
    unigrams, n_total, n_types = Unigrams(t[: K + 2], float(t[K + 2]), float(t[K + 3])), int(t[K + 3]), int(t[K + 4])
    hot = max(n_total / min(4 * parts, HOT), 1.0)
    # a task has a few blocks and what the tables say of them, however many blocks there are
    n_blocks = max(shuffle_partitions(spark), -(-base.count() // BLOCKS_A_TASK))
    asking = base.repartition(n_blocks, "block")

    def ask_pairs(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        for row in left.to_pylist():
            b = Block(row)
            b.words(right.to_pylist())
            b.pairs(texts, hot, parts)
            out += [(row["block"], *r) for r in b.pair_request(unigrams.p(b.count))]
        kinds = [pa.int64(), pa.int32(), pa.bool_(), *[pa.binary()] * 5]
        return pa.table({n: pa.array([r[i] for r in out], k) for i, (n, k) in enumerate(zip(["block", "part", "hot", "a", "b", "c", "d", "e"], kinds, strict=True))})

    asked = asking.groupBy("block").cogroup(words.where("block >= 0").repartition(n_blocks, "block").groupBy("block")).applyInArrow(ask_pairs, "block long, part int, hot boolean, a binary, b binary, c binary, d binary, e binary")
    pairs = written(asked.repartition(parts, "part").groupBy("part").applyInArrow(_pair_task, _ANSWER), "pairs")
    d2 = discounts(_sum_tallies(pairs)[: K + 2])
    hot_sums = spark.sparkContext.broadcast(_hot_sums(pairs))

    def add_up(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        answers = right.to_pylist()
        for row in left.to_pylist():
            b = Block(row)
            b.words([r for r in answers if r["level"] == 1])
            b.pairs(texts, hot, parts)
            p1 = unigrams.p(b.count)
            logp = np.log10(p1[b.w])
            order = iter(sorted((r for r in answers if r["level"] == 2), key=lambda r: (r["part"], r["hot"])))
            edge = np.flatnonzero(np.diff(b.part[b.order] * 2 + b.hot[b.order])) + 1
            for x in np.split(b.order, edge):
                if not len(x):
                    continue
                r = next(order)
                count = unpack(r["a"])
                history, place = np.unique(b.hid[x], return_inverse=True)
                if r["hot"]:
                    sums = [hot_sums.value[int(k)] for k in history]
                    n, low = np.array([s for s, _ in sums]), np.array([q for _, q in sums])
                else:
                    n, low = unpack(r["b"]).reshape(-1, K + 1), np.frombuffer(r["c"], "<f8")
                total = np.zeros(len(history))
                total[place] = b.hcount[x]
                alpha, over = backoff(total, n[:, :K], n[:, K], low, d2)
                logp[x] = np.log10(np.where(count > 0, discounted(count, d2) / over[place], alpha[place] * p1[b.w[x]]))
            n_docs = len(b.lens)
            sums = lambda v: np.bincount(b.doc, v, n_docs)
            flat = np.log10((b.count + 1) / (n_total + n_types + 1))
            cols = [pa.array(row["doc_ids"], pa.int64()), pa.array(np.frombuffer(row["train"], "u1") == 0), pa.array(b.lens), pa.array(sums(b.count[b.tokens] > 0).astype(np.int64)), pa.array(np.full(n_docs, n_total)), pa.array(sums(flat[b.tokens])), pa.array(sums(logp[b.pair_of]))]
            out.append(pa.table(cols, names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]))
        return pa.concat_tables(out)

    answers = words.where("block >= 0").withColumn("level", F.lit(1)).unionByName(pairs.where("block >= 0").withColumn("level", F.lit(2)))
    return asking.groupBy("block").cogroup(answers.repartition(n_blocks, "block").groupBy("block")).applyInArrow(add_up, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
