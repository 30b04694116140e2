"""Suffix-array dedup: sampled suffixes are merge-sorted in front-coded runs, and equal strings found among neighbours.

Two equal 400-byte strings have the same least-hashed 200-byte string at the same place. So it is enough to sort the
suffixes that start at such places (anchors): each 400-byte string belongs to one anchor, and its equals belong to anchors
whose suffixes share 200 bytes or more with that anchor's, which makes them neighbours in the sorted order.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.llm.common import shuffle_partitions, text_or_empty, written
from graphrefresh.llm.near_dup import mix

SPAN, ANCHOR = 400, 200
ROOM = SPAN - ANCHOR
#: Bytes hashed at a time; places must fit the low 24 bits of a key.
CHUNK = 2 << 20
#: Suffixes of a sorted run, and about as many as a merge task gets.
RUN, PART = 20_000, 40_000
_BASE = 0x9E3779B97F4A7C15 | 1


@cache
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base modulo 2**64, and of its inverse."""
    with np.errstate(over="ignore"):
        out = []
        for base in (_BASE, pow(_BASE, -1, 1 << 64)):
            p = np.full(n, base, np.uint64)
            p[0] = 1
            out.append(np.multiply.accumulate(p))
    return tuple(out)


def _prefix(data: np.ndarray) -> np.ndarray:
    power = _powers(CHUNK + 4 * SPAN)[0]
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[: len(data)], out=out[1:])
    return out


def anchors(pieces: list[bytes]) -> tuple[np.ndarray, ...]:
    """(piece, place, before, after, hash) of every anchor: it owns the strings that start from ``before`` to ``after`` bytes before it."""
    data = np.frombuffer(b"".join(pieces), np.uint8)
    n = len(data) - SPAN + 1
    empty = np.zeros(0, np.int64)
    if n <= 0:
        return empty, empty, empty, empty, empty.astype(np.uint64)
    ends = np.cumsum([len(p) for p in pieces])
    c = _prefix(data)
    h = mix((c[ANCHOR:] - c[:-ANCHOR]) * _powers(CHUNK + 4 * SPAN)[1][: len(c) - ANCHOR])
    key = (h & ~np.uint64(0xFFFFFF)) | np.arange(len(h), dtype=np.uint64)
    w = ROOM + 1
    padded = np.full(-(-len(key) // w) * w, ~np.uint64(0))
    padded[: len(key)] = key
    rows = padded.reshape(-1, w)
    left = np.minimum.accumulate(rows, axis=1).ravel()
    right = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    start = np.arange(n)
    piece = np.repeat(np.arange(len(pieces)), [len(p) for p in pieces])[:n]
    ok = start + SPAN <= ends[piece]
    start, piece = start[ok], piece[ok]
    if not len(start):
        return empty, empty, empty, empty, empty.astype(np.uint64)
    place = (np.minimum(right[start], left[start + w - 1]) & np.uint64(0xFFFFFF)).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
    last = np.concatenate([first[1:], [len(place)]]) - 1
    place, piece = place[first], piece[first]
    origin = ends[piece] - np.array([len(p) for p in pieces])[piece]
    return piece, place - origin, place - start[first], place - start[last], h[place]


def _pieces(texts: list[bytes], chunk: int | None = None) -> Iterator[list[tuple[int, int, bytes]]]:
    """Groups of (text, offset, bytes) of ``chunk`` (CHUNK) bytes or less; longer texts overlap so that each string is in one piece."""
    chunk = chunk or CHUNK
    group, size = [], 0
    for i, t in enumerate(texts):
        for off in range(0, max(1, len(t) - SPAN + 1), chunk - SPAN):
            part = t[off : off + chunk - 1]
            if group and size + len(part) > chunk:
                yield group
                group, size = [], 0
            group.append((i, off, part))
            size += len(part)
    if group:
        yield group


def anchor_rows(docs: DataFrame) -> DataFrame:
    """``doc_id, text_hash, anchor, at``: the anchors of every row; ``at`` packs place, before and after. An anchor in the overlap of two pieces has a row for each, with one place."""
    chunk = CHUNK

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 2000):
                part = b.slice(lo, 2000)
                texts = [t.encode("utf-8", "surrogatepass") for t in part.column(2).to_pylist()]
                for group in _pieces(texts, chunk):
                    piece, place, before, after, h = anchors([p for _, _, p in group])
                    if not len(piece):
                        continue
                    text = np.array([i for i, _, _ in group])[piece]
                    place = place + np.array([o for _, o, _ in group])[piece]
                    at = (place << 16) | (before << 8) | after
                    rows = pa.array(text)
                    yield pa.RecordBatch.from_arrays([part.column(0).take(rows), part.column(1).take(rows), pa.array(h.view(np.int64)), pa.array(at)], ["doc_id", "text_hash", "anchor", "at"])

    text = text_or_empty()
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("text_hash"), text.alias("text")).mapInArrow(run, "doc_id long, text_hash long, anchor long, at long")


def common(a: bytes, b: bytes, at: int) -> int:
    """Length of the common prefix of two strings that agree up to ``at``."""
    n, step = min(len(a), len(b)), 16
    while at < n:
        x, y = a[at : at + step], b[at : at + step]
        if x != y:
            m = min(len(x), len(y))
            d = int.from_bytes(x[:m], "big") ^ int.from_bytes(y[:m], "big")
            return at + m - (d.bit_length() + 7) // 8
        at += step
        step *= 2
    return n


def front_code(keys: list[bytes]) -> tuple[np.ndarray, list[bytes]]:
    """Shared length with the one before, and the rest, of sorted strings."""
    shared = [0] * len(keys)
    for i in range(1, len(keys)):
        shared[i] = common(keys[i - 1], keys[i], 0)
    return np.array(shared, np.int64), [k[s:] for k, s in zip(keys, shared, strict=True)]


def merge_runs(runs: list[Iterator[tuple[int, bytes, object]]]) -> Iterator[tuple[int, bytes, object]]:
    """Merge sorted runs of (length shared with the run's last, string, payload) into one, giving the length shared with the last of all.

    A loser tree in which every loser remembers how much it shares with the winner that beat it. A longer shared prefix
    wins without a look at the strings, and where prefixes are as long, comparison goes on behind them, so no byte is
    compared again that is known to be equal.
    """
    k = 1
    while k < len(runs):
        k *= 2
    head: list = [next(r, None) for r in runs] + [None] * (k - len(runs))
    shared = [0] * k
    tree = [0] * k

    def beats(a: int, b: int) -> bool:
        """Whether a's head comes first; the loser's shared length becomes that with the winner."""
        x, y = head[a], head[b]
        if y is None:
            return True
        if x is None:
            return False
        p, q = shared[a], shared[b]
        if p != q:
            return p > q
        s, t = x[1], y[1]
        n = common(s, t, p)
        if n == len(s) or (n < len(t) and s[n] < t[n]):
            shared[b] = n
            return True
        shared[a] = n
        return False

    def build(node: int) -> int:
        if node >= k:
            return node - k
        a, b = build(2 * node), build(2 * node + 1)
        won, lost = (a, b) if beats(a, b) else (b, a)
        tree[node] = lost
        return won

    won = build(1) if k > 1 else 0
    while head[won] is not None:
        _, key, load = head[won]
        yield shared[won], key, load
        head[won] = nxt = next(runs[won], None)
        shared[won] = nxt[0] if nxt else 0
        node = (won + k) // 2
        while node:
            other = tree[node]
            if not beats(won, other):
                tree[node], won = won, other
            node //= 2


def _coded_runs(parts: int):
    """Arrow function from texts with their surviving anchors to front-coded runs, one row per run and merge task."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple[int, bytes, bytes, bytes, int, int]] = []

        def flush() -> Iterator[pa.RecordBatch]:
            rows.sort(key=lambda r: r[:2])
            i = 0
            while i < len(rows):
                j = i
                while j < len(rows) and rows[j][0] == rows[i][0]:
                    j += 1
                own = rows[i:j]
                shared, rest = front_code([r[1] for r in own])
                cols = [[own[0][0]], [shared.astype("<u2").tobytes()], [np.array([len(x) for x in rest], "<u2").tobytes()], [b"".join(rest)], [np.array([len(r[2]) for r in own], "u1").tobytes()], [b"".join(r[2] for r in own)], [b"".join(r[3] for r in own)], [np.array([r[4] for r in own], "<i8").tobytes()], [np.array([r[5] for r in own], "u1").tobytes()]]
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *[pa.array(c, pa.binary()) for c in cols[1:]]], _RUN_NAMES)
                i = j
            rows.clear()

        for b in batches:
            for content, text, at, anchor in zip(*[b.column(i).to_pylist() for i in range(4)], strict=True):
                data = text.encode("utf-8", "surrogatepass")
                for packed, h in zip(at, anchor, strict=True):
                    p, before, after = packed >> 16, packed >> 8 & 255, packed & 255
                    rows.append((h % parts, data[p : p + SPAN - after], data[p - before : p], content, p, after))
                if len(rows) >= RUN:
                    yield from flush()
        yield from flush()

    return run


_RUN_NAMES = ["part", "shared", "rest_len", "rest", "left_len", "lefts", "owners", "places", "afters"]
_RUN_SCHEMA = "part int, " + ", ".join(f"{n} binary" for n in _RUN_NAMES[1:])


def _decode(row: dict) -> Iterator[tuple[int, bytes, tuple]]:
    shared, lens, llens = np.frombuffer(row["shared"], "<u2").tolist(), np.frombuffer(row["rest_len"], "<u2").tolist(), np.frombuffer(row["left_len"], "u1").tolist()
    places, afters = np.frombuffer(row["places"], "<i8").tolist(), np.frombuffer(row["afters"], "u1").tolist()
    a = b = 0
    key = b""
    for i, (s, n, m) in enumerate(zip(shared, lens, llens, strict=True)):
        key = key[:s] + row["rest"][a : a + n]
        yield s, key, (row["lefts"][b : b + m], row["owners"][16 * i : 16 * i + 16], places[i], afters[i])
        a, b = a + n, b + m


def _same_bytes(data: np.ndarray, x: np.ndarray, y: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether the strings that start ``a`` bytes before the anchors of contexts ``x`` and ``b`` before those of ``y`` are equal, from how far the pairs of contexts agree on either side."""
    pair, which = np.unique(x.astype(np.int64) * len(data) + y, return_inverse=True)
    left, right = np.empty(len(pair), np.int64), np.empty(len(pair), np.int64)
    for lo in range(0, len(pair), 20_000):
        p = pair[lo : lo + 20_000]
        differ = data[p // len(data)] != data[p % len(data)]
        before, after = differ[:, :ROOM][:, ::-1], differ[:, ROOM:]
        left[lo : lo + 20_000] = np.where(before.any(axis=1), before.argmax(axis=1), ROOM)
        right[lo : lo + 20_000] = np.where(after.any(axis=1), after.argmax(axis=1), SPAN)
    return (a == b) & (a <= left[which]) & (SPAN - a <= right[which])


def _by_bytes(data: np.ndarray, rows: np.ndarray, before: np.ndarray, cluster: np.ndarray) -> np.ndarray:
    """Which strings another context of the cluster has too, found by the strings themselves."""
    keys = [(int(cluster[r]), int(a), data[r, ROOM - a : ROOM + SPAN - a].tobytes()) for r, a in zip(rows.tolist(), before.tolist(), strict=True)]
    often = Counter(keys)
    return np.array([often[k] > 1 for k in keys])


def _equal_strings(rights: list[bytes], lefts: list[bytes], after: np.ndarray, weight: np.ndarray, cluster: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each context the most and the fewest bytes before its anchor at which a string starts that another context (or the same, if it is there twice) has too; -1 for none.

    Hashes bring candidates together, bytes decide.
    """
    n, before = len(rights), np.array([len(x) for x in lefts])
    data = np.frombuffer(b"".join(a.rjust(ROOM, b"\0") + r.ljust(SPAN, b"\0") for a, r in zip(lefts, rights, strict=True)), np.uint8).reshape(n, ROOM + SPAN)
    most, least = np.full(n, -1), np.full(n, -1)
    power, inverse = _powers(CHUNK + 4 * SPAN)
    c = np.zeros((n, ROOM + SPAN + 1), np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[: ROOM + SPAN], axis=1, out=c[:, 1:])
    width = max(1, 500_000 // n)
    for lo in range(0, ROOM + 1, width):
        a = np.arange(lo, min(lo + width, ROOM + 1))
        own = (a >= after[:, None]) & (a <= before[:, None])
        r, k = np.nonzero(own)
        if not len(r):
            continue
        h = (c[r, ROOM + SPAN - a[k]] - c[r, ROOM - a[k]]) * inverse[ROOM - a[k]]
        key = mix(h + mix(a[k].astype(np.uint64) * np.uint64(_BASE) + mix(cluster[r].astype(np.uint64))))
        order = np.argsort(key)
        eq = np.flatnonzero(key[order][1:] == key[order][:-1])
        one, two = order[eq], order[eq + 1]
        hit = weight[r] > 1
        same = _same_bytes(data, r[one], r[two], a[k[one]], a[k[two]])
        if same.all():
            hit[one] = hit[two] = True
        else:  # different strings met in one hash: tell them apart by their bytes
            hit |= _by_bytes(data, r, a[k], cluster)
        r, k = r[hit], a[k[hit]]
        np.maximum.at(most, r, k)
        low = np.full(n, SPAN)
        np.minimum.at(low, r, k)
        least = np.where((low < SPAN) & ((least < 0) | (low < least)), low, least)
    return most, least


def merge_part(rows: pa.Table) -> pa.Table:
    """Merge the runs of one task and report the stretch of bytes that each anchor's repeated strings cover."""
    out: tuple[list, list, list] = ([], [], [])
    contexts: dict[tuple, list] = {}  # of clusters: suffixes that share an anchor
    number = 0

    def resolve() -> None:
        keep = list(contexts.items())
        if keep:
            most, least = _equal_strings([k[1] for k, _ in keep], [k[2] for k, _ in keep], np.array([k[3] for k, _ in keep]), np.array([len(v) for _, v in keep]), np.array([k[0] for k, _ in keep]))
            for (_, owners), hi, lo in zip(keep, most.tolist(), least.tolist(), strict=True):
                if hi >= 0:
                    for owner, place in owners:
                        out[0].append(owner)
                        out[1].append(place - hi)
                        out[2].append(place - lo + SPAN)
        contexts.clear()

    for shared, key, (left, owner, place, after) in merge_runs([_decode(r) for r in rows.to_pylist()]):
        if shared < ANCHOR:
            number += 1
            if len(contexts) >= 2000:
                resolve()
        contexts.setdefault((number, key, left, after), []).append((owner, place))
    resolve()
    return pa.table({"content": pa.array(out[0], pa.binary()), "start": pa.array(out[1], pa.int64()), "stop": pa.array(out[2], pa.int64())})


def _kept(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        cols: list[list] = [[], [], [], []]
        for content, text, spans in zip(*[b.column(i).to_pylist() for i in range(3)], strict=True):
            data, merged = text.encode("utf-8", "surrogatepass"), []
            for s in sorted((x["start"], x["stop"]) for x in spans):
                if merged and s[0] <= merged[-1][1]:
                    merged[-1][1] = max(merged[-1][1], s[1])
                else:
                    merged.append(list(s))
            at, rest = 0, hashlib.sha256()
            for a, z in merged:
                rest.update(data[at:a])
                at = z
            rest.update(data[at:])
            cols[0].append(content)
            cols[1].append([{"start": a, "stop": z} for a, z in merged])
            cols[2].append(sum(z - a for a, z in merged))
            cols[3].append(rest.hexdigest())
        kind = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.binary()), pa.array(cols[1], kind), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.string())], ["content", "spans", "n_removed", "rest_sha256"])


def repeated_bytes(docs: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans``: one row per row of ``docs`` (doc_id, text).

    Removed is every byte of the UTF-8 text covered by a 400-byte string that starts anywhere else too, be it in the same
    row. ``spans`` are the maximal removed runs as byte offsets, ``kept_sha256`` digests the remaining bytes.

    Texts that occur twice are removed whole, if long enough, and sorted once. Of all other texts only the anchors whose
    200 bytes occur twice are sorted. A null text is an empty one; null and repeated ids are rows like any other, so two
    rows with one long text lose it; extra columns are ignored; no rows give no rows.
    """
    spark = docs.sparkSession
    text = text_or_empty()
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    rows = docs.select("doc_id", F.unhex(F.md5("text")).alias("content"), F.xxhash64("text").alias("text_hash"), F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("sha"))
    rows = written(rows, "texts")
    marked = written(anchor_rows(docs), "anchors")
    # copies of one text have its anchors at the same places; any other text or place is a second occurrence
    place = F.shiftright("at", 16)
    twice = marked.groupBy("anchor").agg(F.min("text_hash").alias("a"), F.max("text_hash").alias("z"), F.min(place).alias("p"), F.max(place).alias("q")).where("a <> z OR p <> q").select(F.col("anchor").alias("x"))
    twice = written(twice, "twice")  # joined anew, so that Spark can split a hot anchor
    texts = rows.groupBy("content").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.first("text_hash").alias("h"))
    places = marked.join(twice, F.col("anchor") == F.col("x"), "left_semi").join(texts.select("content", "rep", "h"), (F.col("text_hash") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("rep")))
    places = written(places.groupBy("content").agg(F.first("rep").alias("rep"), F.first("h").alias("h"), F.collect_set(F.struct("at", "anchor")).alias("p")), "places")
    n = places.agg(F.sum(F.size("p"))).first()[0] or 0
    parts = max(shuffle_partitions(spark), -(-n // PART))
    own = docs.withColumn("text_hash", F.xxhash64("text")).join(places, (F.col("text_hash") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("rep")))
    own = written(own.where(F.unhex(F.md5("text")) == F.col("content")).select("content", "text", F.col("p.at").alias("at"), F.col("p.anchor").alias("anchor")).dropDuplicates(["content"]), "candidates")
    coded = own.mapInArrow(_coded_runs(parts), _RUN_SCHEMA)
    spans = coded.repartition(parts, "part").groupBy("part").applyInArrow(merge_part, "content binary, start long, stop long")
    spans = spans.groupBy("content").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))
    cut = own.select(F.col("content").alias("c"), "text").join(spans, F.col("c") == F.col("content")).select("content", "text", "spans").mapInArrow(_kept, "content binary, spans array<struct<start: long, stop: long>>, n_removed long, rest_sha256 string")
    facts = texts.select("content", "copies").join(cut, "content", "left").withColumnRenamed("content", "c")
    out = rows.join(facts, F.col("content") == F.col("c"))
    whole = (F.col("copies") > 1) & (F.col("n_bytes") >= SPAN)
    spans = F.when(whole, F.array(F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("stop")))).otherwise(F.coalesce("spans", F.expr("array()").cast("array<struct<start: long, stop: long>>")))
    return out.withColumn("spans", spans).select(
        "doc_id", "n_bytes", F.when(whole, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0).cast("long"))).alias("n_removed"), F.size("spans").cast("long").alias("n_spans"),
        F.when(whole, F.sha2(F.lit(""), 256)).otherwise(F.coalesce("rest_sha256", "sha")).alias("kept_sha256"), "spans",
    )
