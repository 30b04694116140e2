"""Quality rules: per-document counts, and lines that too many documents of one host repeat."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphrefresh.llm.common import BLANK_CHARS, let, text_or_empty, unused, words_of

MIN_WORDS = 50
#: A line is boilerplate of its host when at least MIN_DOCS different documents and a SHARE of the host's have it.
MIN_DOCS, SHARE = 10, 0.05
#: A document is depleted when less than this share of its words is left.
KEEP_SHARE = 0.5


def _repeat_words(words: Column) -> Column:
    """Words covered by 3-word windows that the text has twice or more. Windows are sorted by hash; equal neighbours are compared in full."""

    def covered(w: Column, h: Column) -> Column:
        keyed = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def marked(s: Column) -> Column:
            same = lambda a, b: (a["h"] == b["h"]) & (w[a["i"]] == w[b["i"]]) & (w[a["i"] + 1] == w[b["i"] + 1]) & (w[a["i"] + 2] == w[b["i"] + 2])
            hit = lambda e, i: ((i > 0) & same(e, s[F.greatest(i - 1, F.lit(0))])) | ((i < F.size(s) - 1) & same(e, s[F.least(i + 1, F.size(s) - 1)]))
            starts = F.transform(F.filter(s, hit), lambda e: F.array(e["i"], e["i"] + 1, e["i"] + 2))
            return F.size(F.array_distinct(F.flatten(starts)))

        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(let(keyed, marked))

    def windows(w: Column) -> Column:
        hashes = F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(w[i], w[i + 1], w[i + 2]))
        return F.when(F.size(w) < 4, F.lit(0)).otherwise(let(hashes, lambda h: covered(w, h)))

    return let(words, windows)


def base_counts(docs: DataFrame, *keep: str) -> DataFrame:
    """``keep`` columns plus n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long) and base_failed of each whole text."""
    text = text_or_empty()
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.translate(x, BLANK_CHARS, "") != "")
    out = docs.select(
        *keep,
        F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")).cast("long").alias("n_words"),
        F.length(F.translate(text, BLANK_CHARS, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        _repeat_words(words_of(text)).cast("long").alias("n_repeat_words"),
    )
    return out.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")))


def normalised(line: Column) -> Column:
    """Lower case, digits as 0, blanks as one space, none at the ends."""
    plain = F.translate(F.lower(line), "123456789\t\n\x0b\x0c\r", "000000000     ")
    return F.trim(F.when(F.contains(plain, F.lit("  ")), F.regexp_replace(plain, " +", " ")).otherwise(plain))


def line_rows(docs: DataFrame, key: str) -> DataFrame:
    """One row per line with a word: ``key, host, content, line_no, line, line_hash, line_words``; content is a hash of the whole text."""
    text = text_or_empty()
    out = docs.select(key, F.col("source").alias("host"), F.xxhash64(text).alias("content"), F.posexplode(F.split(text, "\n", -1)).alias("line_no", "line"))
    out = out.where(F.translate("line", BLANK_CHARS, "") != "")
    return out.withColumns({"line_hash": F.xxhash64(normalised(F.col("line"))), "line_words": F.regexp_count("line", F.lit(r"[^\x20\x09-\x0D]+")).cast("long")})


def frequent_lines(lines: DataFrame, docs: DataFrame, min_docs: int = MIN_DOCS, share: float = SHARE) -> DataFrame:
    """``host, line_hash, n_docs`` of boilerplate lines. Documents with the same text count once; both aggregates combine map-side, so a hot host or line costs no more than any other."""
    sizes = docs.select(F.col("source").alias("host"), F.xxhash64(text_or_empty()).alias("content")).distinct().groupBy("host").agg(F.count(F.lit(1)).alias("host_docs"))
    seen = lines.select("host", "line_hash", "content").distinct().groupBy("host", "line_hash").agg(F.count(F.lit(1)).alias("n_docs")).where(F.col("n_docs") >= min_docs)
    return seen.join(sizes.withColumnRenamed("host", "h"), F.col("host").eqNullSafe(F.col("h"))).where(F.col("n_docs") >= share * F.col("host_docs")).select("host", "line_hash", "n_docs")


def depletion(docs: DataFrame, key: str, min_docs: int = MIN_DOCS, share: float = SHARE) -> DataFrame:
    """``key, lost_words, lost_lines array<int>`` of the documents that have boilerplate lines. Rows that share a key count once."""
    lines = line_rows(docs, key)
    hot = frequent_lines(lines, docs, min_docs, share).select(F.col("host").alias("h"), F.col("line_hash").alias("lh"))
    hit = lines.select(key, "host", "line_no", "line_hash", "line_words").join(hot, (F.col("line_hash") == F.col("lh")) & F.col("host").eqNullSafe(F.col("h")), "left_semi")
    hit = hit.groupBy(key).agg(F.collect_set(F.struct("line_no", "line_words")).alias("lost"))
    return hit.select(key, F.aggregate("lost", F.lit(0).cast("long"), lambda n, x: n + x["line_words"]).alias("lost_words"), F.col("lost.line_no").alias("lost_lines"))


def _keyed(docs: DataFrame, key: str = "_key") -> DataFrame:
    """Rows with the same id, text and host share a key, and so a verdict."""
    return docs.withColumn(key, F.md5(F.to_json(F.struct(F.col("doc_id"), F.md5(text_or_empty()).alias("t"), F.col("source")), {"ignoreNullFields": "false"})))


def judge(docs: DataFrame, min_docs: int = MIN_DOCS, share: float = SHARE, keep_share: float = KEEP_SHARE) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text, source): the counts of ``base_counts``, lost_words and kept.

    ``kept`` is false where the base rules fail or where boilerplate lines leave less than ``keep_share`` of the words. A
    null text has no words and fails; a null host is a host of its own; a null doc_id is judged like any other; rows that
    repeat another get the same verdict. Lines without a word are never counted. Extra columns are ignored; no rows give
    no rows. No text is shuffled: only ids, hashes and counts are.
    """
    docs = _keyed(docs.select("doc_id", "text", "source"))
    lost = depletion(docs, "_key", min_docs, share).select(F.col("_key").alias("_k"), "lost_words")
    out = base_counts(docs, "doc_id", "_key").join(lost, F.col("_key") == F.col("_k"), "left").withColumn("lost_words", F.coalesce("lost_words", F.lit(0).cast("long")))
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("n_words") - F.col("lost_words") >= keep_share * F.col("n_words"))).drop("_k", "_key")


def clean(docs: DataFrame, min_docs: int = MIN_DOCS, share: float = SHARE, keep_share: float = KEEP_SHARE) -> DataFrame:
    """The documents that ``judge`` keeps, with all their columns, without their boilerplate lines; n_chars, if there, follows the text.

    A null or empty text has no words and goes; a null host is a host of its own; null and repeated ids, and repeated
    rows, are judged like any other and stay as often as they occur; extra columns stay, whatever they are called; no rows
    give no rows.
    """
    key, lines = unused("_key", docs), unused("_lines", docs)
    keyed = _keyed(docs, key)
    slim = keyed.select(F.col(key).alias("_key"), "text", "source")
    lost = depletion(slim, "_key", min_docs, share).withColumnRenamed("_key", "_k")
    counts = base_counts(slim, "_key").where(~F.col("base_failed")).select("_key", "n_words").distinct()
    verdict = counts.join(lost, F.col("_key") == F.col("_k"), "left").where(F.col("lost_words").isNull() | (F.col("n_words") - F.col("lost_words") >= keep_share * F.col("n_words")))
    k = unused("_verdict", keyed)
    out = keyed.join(verdict.select(F.col("_key").alias(k), F.col("lost_lines").alias(lines)), F.col(key) == F.col(k))
    rest = F.array_join(F.filter(F.split("text", "\n", -1), lambda x, i: ~F.array_contains(lines, i)), "\n")
    out = out.withColumn("text", F.when(F.col(lines).isNull(), F.col("text")).otherwise(rest))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])
