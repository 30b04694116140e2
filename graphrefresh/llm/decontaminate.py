"""Benchmark decontamination: SimHash fingerprints of item-sized windows, Hamming blocks, exact weighted-shingle similarity."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.llm.common import let, text_or_empty, unused, words_of, written

N_WORDS, NUM, DEN = 5, 4, 5  # five words a shingle; similarity of NUM / DEN or more
#: Fingerprints have 64 bits, in BLOCKS equal blocks: two that differ in RADIUS bits at most differ in RADIUS // BLOCKS at most in one of them.
RADIUS, BLOCKS = 10, 4
#: Tables of the benchmark are broadcast up to this many rows and this many bytes of their files; larger ones are joined by shuffle.
BROADCAST_ROWS, BROADCAST_BYTES = 500_000, 16 << 20


def small(df: DataFrame) -> DataFrame:
    """Broadcast a written table of the benchmark if it is small enough."""
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return F.broadcast(df) if size <= BROADCAST_BYTES and df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def _lower_words(text: Column) -> Column:
    return words_of(F.lower(text))


def _grams(words: Column, k: int, make) -> Column:
    """``make`` of the k columns of each run of k words; empty for fewer words."""
    return let(words, lambda w: F.when(F.size(w) < k, F.array().cast("array<bigint>") if make is F.xxhash64 else F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(0), F.size(w) - k), lambda i: make(*[w[i + j] for j in range(k)]))))


def _joined(*words: Column) -> Column:
    return F.concat_ws(" ", *words)


def simhash(words: Column) -> Column:
    """Bit b is set when most words' hashes have it; a word counts as often as it occurs."""

    def bits(h: Column) -> Column:
        votes = lambda b: F.aggregate(h, F.lit(0), lambda n, x: n + F.getbit(x, b).cast("int"))
        return F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), lambda f, b: F.when(2 * votes(b) > F.size(h), f.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), b))).otherwise(f))

    return let(F.transform(words, lambda w: F.xxhash64(w)), bits)


def blocks_of(fingerprint: Column) -> Column:
    """``array<bigint>`` of the blocks, each tagged with its number."""
    width = 64 // BLOCKS
    return F.array(*[F.shiftrightunsigned(fingerprint, k * width).bitwiseAND(F.lit((1 << width) - 1)) * BLOCKS + k for k in range(BLOCKS)])


def probes_of(fingerprint: Column, radius: int = RADIUS) -> Column:
    """All blocks that a fingerprint within ``radius`` can have: of each block those that differ in radius // BLOCKS bits at most.

    An item's probes are looked up by a window's four blocks. With 65,536 values a block and 137 probes, a window meets one
    item in 120 by chance.
    """
    width = 64 // BLOCKS
    masks = [sum(1 << i for i in bits) for n in range(radius // BLOCKS + 1) for bits in combinations(range(width), n)]
    flips = F.lit(",".join(str(m * BLOCKS) for m in masks))
    return F.flatten(F.transform(blocks_of(fingerprint), lambda b: F.transform(F.split(flips, ",").cast("array<bigint>"), lambda m: b.bitwiseXOR(m))))


def shared_grams(a: Column, b: Column) -> Column:
    """Size of the intersection of two bags."""
    count = lambda xs, x: F.size(F.filter(xs, lambda y: y == x))
    return let(a, lambda p: let(b, lambda q: F.aggregate(F.array_intersect(p, q), F.lit(0), lambda n, x: n + F.least(count(p, x), count(q, x)))))


def items_of(benchmark: DataFrame) -> DataFrame:
    """``item_id, words, m, k, fingerprint`` of the items with a word; k is the length of their shingles."""
    items = benchmark.select("item_id", _lower_words(F.col("text")).alias("words")).where(F.size("words") > 0)
    return items.withColumns({"m": F.size("words"), "k": F.least(F.size("words"), F.lit(N_WORDS)), "fingerprint": simhash(F.col("words"))})


def _shingles(words: Column, m: Column) -> Column:
    """Shingles, as strings, of an item of m words or of a window of its size; one shingle where m is less than N_WORDS."""
    return F.when(m >= N_WORDS, _grams(words, N_WORDS, _joined)).otherwise(F.array(F.array_join(words, " ")))


def rare_shingles(items: DataFrame) -> DataFrame:
    """``rare, size, item_id``: the shingles, rarest in the benchmark first, of which a window at NUM / DEN has one at least.

    They make up more than 1 - NUM / DEN of the item's bag, so that without them too few are left to share.
    """
    grams = items.select("item_id", "m", F.md5(F.array_join("words", " ")).alias("key"), F.explode(_shingles(F.col("words"), F.col("m"))).alias("rare"))
    grams = grams.groupBy("item_id", "key", "m", "rare").agg(F.count(F.lit(1)).alias("n"))
    often = grams.groupBy("m", "rare").agg(F.count(F.lit(1)).alias("often"))
    item = Window.partitionBy("item_id", "key")
    before = F.coalesce(F.sum("n").over(item.orderBy("often", "rare").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    grams = grams.join(often, ["m", "rare"]).withColumns({"before": before, "all": F.sum("n").over(item)})
    return grams.where(DEN * F.col("before") <= (DEN - NUM) * F.col("all")).select("rare", F.col("m").alias("size"), "item_id").distinct()


def contaminated(docs: DataFrame, benchmark: DataFrame, radius: int = RADIUS) -> DataFrame:
    """``content, item_id, similarity, start_word, window_words``: the best window of each text and item that it leaks.

    A window leaks an item of its own size when their bags of 5-word shingles, in lower case, have a weighted Jaccard
    similarity of 0.8 or more (an item of fewer words is one shingle). Windows are laid wherever a text has a shingle of
    an item, so that it falls in each of the item's places for it: elsewhere the similarity is 0. A window is compared
    by its shingles with the items of its size whose fingerprint is within ``radius`` bits, found block by block, and
    with those of which it has a rare shingle. Words changed at an item's ends may flip more bits, so the fingerprints
    alone would miss leaks; the rare shingles miss none. Of the text only ids and places of hits are kept until windows
    are cut.
    """
    items = written(items_of(benchmark), "items")
    hits = None
    rows = docs.select("doc_id", F.unhex(F.md5(text_or_empty())).alias("content"), _lower_words(F.col("text")).alias("words"))
    for k in sorted(r[0] for r in items.select("k").distinct().collect()):  # at most five lengths
        own = items.where(F.col("k") == k).select("m", F.posexplode(_grams(F.col("words"), k, F.xxhash64)).alias("item_pos", "gram"))
        own = written(own.select("gram", "m", "item_pos").distinct(), "grams")
        seen = rows.select("doc_id", "content", F.posexplode(_grams(F.col("words"), k, F.xxhash64)).alias("pos", "g"))
        found = seen.join(small(own), F.col("g") == F.col("gram")).select("doc_id", "content", F.struct(F.greatest(F.col("pos") - F.col("item_pos"), F.lit(0)).alias("start"), "m").alias("at"))
        hits = found if hits is None else hits.unionByName(found)
    if hits is None:
        return docs.sparkSession.createDataFrame([], "content binary, item_id long, similarity double, start_word int, window_words int")
    places = hits.groupBy("content").agg(F.min("doc_id").alias("rep"), F.collect_set("at").alias("ats")).withColumnRenamed("content", "c")
    text = docs.select("doc_id", F.unhex(F.md5(text_or_empty())).alias("content"), "text")
    cut = text.join(places, (F.col("content") == F.col("c")) & F.col("doc_id").eqNullSafe(F.col("rep"))).select("content", _lower_words(F.col("text")).alias("words"), "ats")
    windows = cut.select("content", F.explode(let(F.col("words"), lambda w: F.transform("ats", lambda a: F.struct(a["start"].alias("start"), a["m"].alias("m"), F.slice(w, a["start"] + 1, a["m"]).alias("window"))))).alias("x")).select("content", "x.*").distinct()
    windows = written(windows.withColumn("fp", simhash(F.col("window"))), "windows")
    index = items.select("item_id", F.col("m").alias("size"), "fingerprint", F.explode(probes_of(F.col("fingerprint"), radius)).alias("block"))
    index = written(index, "blocks")
    near = windows.select("content", "start", "m", "fp", F.explode(blocks_of(F.col("fp"))).alias("b")).join(small(index), (F.col("b") == F.col("block")) & (F.col("m") == F.col("size")))
    near = near.where(F.bit_count(F.col("fp").bitwiseXOR(F.col("fingerprint"))) <= radius).select("content", "start", "m", "item_id")
    rare = written(rare_shingles(items), "rare")
    own = windows.select("content", "start", "m", F.explode(F.array_distinct(_shingles(F.col("window"), F.col("m")))).alias("shingle"))
    near = near.unionByName(own.join(small(rare), (F.col("shingle") == F.col("rare")) & (F.col("m") == F.col("size"))).select("content", "start", "m", "item_id")).distinct()
    pairs = near.join(windows.drop("fp"), ["content", "start", "m"]).join(small(items.select("item_id", "words", F.col("m").alias("size"))), "item_id").where("m = size")
    pairs = pairs.withColumns({"a": _shingles(F.col("window"), F.col("m")), "b": _shingles(F.col("words"), F.col("m"))}).withColumn("shared", shared_grams(F.col("a"), F.col("b"))).withColumn("all", F.size("a") + F.size("b") - F.col("shared"))
    best = F.max(F.struct((F.col("shared") / F.col("all")).alias("similarity"), (-F.col("start")).alias("s"), F.size("window").alias("n"))).alias("x")
    return pairs.where(DEN * F.col("shared") >= NUM * F.col("all")).groupBy("content", "item_id").agg(best).select("content", "item_id", "x.similarity", (-F.col("x.s")).alias("start_word"), F.col("x.n").alias("window_words"))


def leaks(docs: DataFrame, benchmark: DataFrame, radius: int = RADIUS) -> DataFrame:
    """``doc_id, item_id, similarity, start_word, window_words``: one row per row of ``docs`` and item that it leaks.

    Texts that occur more than once are searched once. A null text or item has no words and leaks nothing; null and
    repeated ids are reported like any other, an item that occurs twice under both its ids; extra columns are ignored; an
    empty table on either side gives no rows.
    """
    found = contaminated(docs, benchmark, radius).withColumnRenamed("content", "c")
    return docs.select("doc_id", F.unhex(F.md5(text_or_empty())).alias("content")).join(found, F.col("content") == F.col("c")).select("doc_id", "item_id", "similarity", "start_word", "window_words")


def clean(docs: DataFrame, benchmark: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The rows of ``docs``, all columns, whose text leaks no item.

    Null and empty texts leak nothing and stay; null and repeated ids and repeated rows stay as often as they occur; extra
    columns stay, whatever they are called; an empty benchmark leaves all rows, no rows give no rows.
    """
    c = unused("_c", docs)
    found = contaminated(docs, benchmark, radius).select(F.col("content").alias(c)).distinct()
    return docs.join(found, F.unhex(F.md5(text_or_empty())) == F.col(c), "left_anti")
