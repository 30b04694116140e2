"""N-gram Jaccard join: MinHash bands find candidates, full n-gram sets decide."""

from __future__ import annotations

import math
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphrefresh.llm.common import text_or_empty, unused, written
from graphrefresh.llm.components import components

N_WORDS, NUM, DEN = 5, 4, 5  # five words a shingle; similarity of NUM / DEN or more
RECALL, MAX_HASHES = 0.998, 128
SEED = 20_240_501
#: Bytes of text that a task compares with as many again.
BLOCK_BYTES = 8 << 20
_WORD = re.compile(r"[^ \t-\r]+")
_MUL = np.uint64(0x9E3779B97F4A7C15)


def choose_bands(similarity: float = NUM / DEN, recall: float = RECALL, max_hashes: int = MAX_HASHES) -> tuple[int, int]:
    """(bands, rows): the most rows a band, and so the fewest false candidates, with which pairs of just that similarity are found with the target recall."""
    best = (max_hashes, 1)
    for rows in range(1, max_hashes + 1):
        bands = math.ceil(math.log(1 - recall) / math.log(1 - similarity**rows))
        if bands * rows > max_hashes:
            break
        best = (bands, rows)
    return best


class _Words(dict):
    def __missing__(self, word: str) -> int:
        import xxhash

        if len(self) > 1_000_000:
            self.clear()
        self[word] = h = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
        return h


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(text: str, known: dict) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the 5-word shingles of a whole text; a shorter text is one shingle, one without words none."""
    words = _WORD.findall(text)
    w = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    n = max(1, len(w) - N_WORDS + 1) if len(w) else 0
    h = np.zeros(n, np.uint64)
    for k in range(min(N_WORDS, len(w))):
        h = (h + w[k : k + n]) * _MUL
        h ^= h >> np.uint64(29)
    return np.unique(mix(h))


def signatures(docs: DataFrame, bands: int, rows: int) -> DataFrame:
    """``doc_id, content, n_bytes, bands`` of every row; no bands for a text without words."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng, known = np.random.default_rng(SEED), _Words()
        a = rng.integers(1, 1 << 63, bands * rows, dtype=np.uint64) | np.uint64(1)
        powers = rng.integers(1, 1 << 63, rows, dtype=np.uint64) | np.uint64(1)
        for b in batches:
            out, size = [], []
            for t in b.column(2).to_pylist():
                s, low = shingles(t, known), None
                size.append(len(t))
                for i in range(0, len(s), 2048):
                    part = ((s[None, i : i + 2048] * a[:, None]) >> np.uint64(32)).min(axis=1)
                    low = part if low is None else np.minimum(low, part)
                out.append(None if low is None else mix((low.reshape(bands, rows) * powers).sum(axis=1, dtype=np.uint64)).astype(np.int64))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(size, pa.int64()), pa.array(out, pa.list_(pa.int64()))], ["doc_id", "content", "n_bytes", "bands"])

    text = text_or_empty()
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.md5(text)).alias("content"), text.alias("text")).mapInArrow(run, "doc_id long, content binary, n_bytes long, bands array<long>")


def _matches(sets: list[np.ndarray]) -> Iterator[tuple[int, np.ndarray]]:
    """For each set the others with which it shares enough, from one pass over the shingles' posting lists."""
    sizes = np.array([len(s) for s in sets])
    doc = np.repeat(np.arange(len(sets)), sizes)
    _, ids = np.unique(np.concatenate(sets) if sets else np.zeros(0, np.uint64), return_inverse=True)
    order = np.argsort(ids, kind="stable")
    posted, starts = doc[order], np.concatenate([[0], np.cumsum(np.bincount(ids))])
    at = np.concatenate([[0], np.cumsum(sizes)])
    for i in range(len(sets)):
        own = ids[at[i] : at[i + 1]]
        a, n = starts[own], starts[own + 1] - starts[own]
        a, n = a[n > 1], n[n > 1]
        if not len(a):
            continue
        shared = np.zeros(len(sets), np.int64)
        for k in range(0, len(a), 4096):  # a long text among many others
            m = n[k : k + 4096]
            shared += np.bincount(posted[np.repeat(a[k : k + 4096] - np.concatenate([[0], np.cumsum(m)[:-1]]), m) + np.arange(m.sum())], minlength=len(sets))
        hit = np.flatnonzero(DEN * shared >= NUM * (sizes + sizes[i] - shared))
        yield i, hit[hit != i]


def verify_group(rows: pa.Table) -> pa.Table:
    """Count each text's true partners in a group (or across two blocks of one) and tie the texts of a class by a few edges."""
    known, seen = _Words(), {}
    for c, t, n, block in zip(*[rows.column(x).to_pylist() for x in ("content", "text", "copies", "block")], strict=True):
        seen.setdefault(c, (t, n, block))  # a repeated row
    content, texts = list(seen), list(seen.values())
    sets = [shingles(t, known) for t, _, _ in texts]
    copies, block = np.array([n for _, n, _ in texts], np.int64), np.array([b for _, _, b in texts], np.int64)
    across = len(set(block.tolist())) > 1 or rows.column("bi")[0].as_py() != rows.column("bj")[0].as_py()
    links, root = np.zeros(len(sets), np.int64), list(range(len(sets)))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for i, hit in _matches(sets):
        if across:
            hit = hit[block[hit] != block[i]]
        links[i] = copies[hit].sum()
        for j in hit[hit < i]:
            x, y = find(i), find(int(j))
            if x != y:
                root[max(x, y)] = min(x, y)
    keep = [i for i in range(len(sets)) if links[i]]
    return pa.table({"content": pa.array([content[i] for i in keep], pa.binary()), "links": pa.array([int(links[i]) for i in keep], pa.int64()), "near": pa.array([content[find(i)] for i in keep], pa.binary())})


def near_duplicates(docs: DataFrame, recall: float = RECALL, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``doc_id, content, class_key, class_id, n_links``: one row per row of ``docs`` (doc_id, text).

    Two documents are linked when their sets of 5-word shingles have a Jaccard similarity of 0.8 or more, or their texts
    are equal. ``class_id`` is the least doc_id that links lead to, ``n_links`` counts the linked documents, copies
    included; ``content`` is the text's md5, ``class_key`` the least such of the class. Copies are one text throughout.

    Texts that share a band are tied to the bucket's least text; the groups so connected, mostly of a few texts, are
    compared by their whole shingle sets. A large group is cut into blocks by text, and each pair of blocks is a task of
    its own, so no task holds more than two blocks and no pair of texts becomes a row.

    A null text is an empty one; texts without words are linked with each other only when equal. A null doc_id belongs to
    its text's class and gives no class_id unless all of the class are null. Rows that repeat an id and text count as
    copies. Extra columns are ignored; no rows give no rows.
    """
    bands, rows = choose_bands(recall=recall)
    signed = written(signatures(docs, bands, rows), "signatures")
    texts = signed.groupBy("content").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.max("n_bytes").alias("n_bytes"))
    one = signed.select("content", "doc_id", "bands").join(texts.select(F.col("content").alias("c"), "rep"), (F.col("content") == F.col("c")) & F.col("doc_id").eqNullSafe(F.col("rep")), "left_semi")
    banded = one.select("content", F.posexplode("bands").alias("band", "value"))
    buckets = banded.groupBy("band", "value").agg(F.min("content").alias("first"), F.max("content").alias("last")).where("first <> last").drop("last")
    edges = banded.join(buckets, ["band", "value"]).select(F.col("content").alias("u"), F.col("first").alias("v"))
    groups = written(components(edges), "groups")
    members = groups.join(texts, F.col("node") == F.col("content")).select("root", "content", "rep", "copies", "n_bytes")
    sizes = members.groupBy("root").agg(F.ceil(F.sum("n_bytes") / block_bytes).cast("int").alias("blocks")).withColumnRenamed("root", "r")
    placed = members.join(sizes, F.col("root") == F.col("r")).withColumn("block", F.pmod(F.xxhash64("content"), F.col("blocks")).cast("long"))
    text = docs.select(F.col("doc_id").cast("long").alias("d"), F.unhex(F.md5(text_or_empty())).alias("t"), text_or_empty().alias("text"))
    full = text.join(placed, (F.col("t") == F.col("content")) & F.col("d").eqNullSafe(F.col("rep")))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks").cast("long") - 1))
    full = full.select("root", "content", "text", "copies", "block", other.alias("other")).select("*", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"))
    found = written(full.groupBy("root", "bi", "bj").applyInArrow(verify_group, "content binary, links long, near binary"), "links")
    classes = written(components(found.select(F.col("content").alias("u"), F.col("near").alias("v"))), "classes")
    counts = found.groupBy("content").agg(F.sum("links").alias("links"))
    ids = texts.join(classes.withColumnRenamed("node", "content"), "content", "left").join(counts, "content", "left")
    ids = ids.select("content", F.coalesce("root", "content").alias("class_key"), "rep", "copies", F.coalesce("links", F.lit(0)).alias("links"))
    least = ids.groupBy("class_key").agg(F.min("rep").alias("class_id"))
    ids = ids.join(least, "class_key").select(F.col("content").alias("c"), F.hex("class_key").alias("class_key"), "class_id", (F.col("links") + F.col("copies") - 1).alias("n_links"))
    return signed.select("doc_id", "content").join(ids, F.col("content") == F.col("c")).select("doc_id", F.hex("content").alias("content"), "class_key", "class_id", "n_links")


def one_of_each(docs: DataFrame, recall: float = RECALL) -> DataFrame:
    """The rows of ``docs``, all columns, without near duplicates: of each class the row with the least doc_id, and of rows that repeat its id and text one.

    Classes without an id keep the row with the least text hash. A null text is an empty one; extra columns stay, whatever
    they are called; no rows give no rows.
    """
    keep = near_duplicates(docs, recall).where(F.col("doc_id").eqNullSafe(F.col("class_id"))).groupBy("class_key").agg(F.min(F.struct("content", "doc_id")).alias("k"))
    content = unused("_content", docs)
    keyed = docs.withColumn(content, F.hex(F.unhex(F.md5(text_or_empty()))))
    c, d = unused("_c", keyed), unused("_d", keyed)
    keep = keep.select(F.col("k.content").alias(c), F.col("k.doc_id").alias(d))
    kept = keyed.join(keep, (F.col(content) == F.col(c)) & F.col("doc_id").cast("long").eqNullSafe(F.col(d)), "left_semi")
    return kept.dropDuplicates([content, "doc_id"]).drop(content)
