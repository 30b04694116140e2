"""Mixing sources to target weights: budgets flow down a domain-language-source tree, and leaves give seeded prefixes of epochs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.llm.common import text_or_empty, unused, written

LEVELS = ("domain", "lang", "source")
#: Integer weights by level and node, 1 for any other: languages lean to English; sources to the first few.
WEIGHTS = {"domain": {"d0": 2, "d1": 3, "d2": 5}, "lang": {"en": 6, "de": 2, "fr": 2, "es": 1}, "source": {"src0": 4, "src1": 2}}
SEED = "mix-1"
#: Hexadecimal digits of the order hash by which a leaf, and each bucket again, is dealt out; about as many documents as are left in a bucket.
DIGITS, BUCKET_ROWS = 2, 1000


def domain_of(source: Column) -> Column:
    """Sources fall into three domains by the number in their name, 0 where there is none."""
    return F.concat(F.lit("d"), F.pmod(F.coalesce(F.try_to_number(F.regexp_extract(source, r"([0-9]{1,9})", 1), F.lit("999999999")).cast("long"), F.lit(0)), F.lit(3)))


def leaves(docs: DataFrame) -> DataFrame:
    """``doc_id, domain, lang, source, tokens``; nulls become empty names, a word is a token."""
    name = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    return docs.select("doc_id", domain_of(name("source")).alias("domain"), name("lang").alias("lang"), name("source").alias("source"), F.regexp_count(text_or_empty(), F.lit(r"[^\x20\x09-\x0D]+")).cast("long").alias("tokens"), F.md5(text_or_empty()).alias("content"))


def weight_of(level: str, weights: dict) -> Column:
    out = F.lit(1)
    for k, v in weights.get(level, {}).items():
        out = F.when(F.col(level) == k, F.lit(int(v))).otherwise(out)
    return out.cast("long")


def budgets(leaf_sizes: DataFrame, share: tuple[int, int] = (3, 5), max_epochs: int = 2, weights: dict | None = None) -> DataFrame:
    """``domain, lang, source, available, budget`` of every leaf; the root gets ``share`` (a fraction) of all tokens.

    A node's budget is dealt to its children in proportion to their weights, none getting more than its subtree can give
    (its tokens times ``max_epochs``). What a full child cannot take goes to its siblings; only when all siblings are full
    would an ancestor's other children get it, and they do, as the caps are those of whole subtrees. Children are filled
    in order of cap over weight, so each share needs only the sums over those before it. Shares are rounded down, so a
    node may keep fewer tokens than it has children. The tree has a row per leaf, however many documents there are.
    """
    weights = WEIGHTS if weights is None else weights
    cap = leaf_sizes.select(*LEVELS, "available", (F.col("available") * max_epochs).alias("cap"))
    top = cap.groupBy("domain").agg(F.sum("cap").alias("cap"), F.sum("available").alias("a"))
    top = top.withColumn("all", F.sum("a").over(Window.partitionBy(F.lit(1)))).withColumn("given", F.expr(f"CAST(`all` AS DECIMAL(28,0)) * {share[0]} DIV {share[1]}"))
    nodes = _deal(top, [], "domain", weights)
    for depth, level in enumerate(LEVELS[1:], 1):
        parents = list(LEVELS[:depth])
        below = cap.groupBy(*LEVELS[: depth + 1]).agg(F.sum("cap").alias("cap"))
        nodes = _deal(below.join(nodes.select(*parents, F.col("budget").alias("given")), parents), parents, level, weights)
    return nodes.select(*LEVELS, "budget").join(cap.select(*LEVELS, "available"), list(LEVELS))


def _deal(children: DataFrame, parents: list[str], level: str, weights: dict) -> DataFrame:
    by = Window.partitionBy(*parents) if parents else Window.partitionBy(F.lit(1))
    before = by.orderBy(F.col("cap") / F.col("w"), level).rowsBetween(Window.unboundedPreceding, -1)
    out = children.withColumn("w", weight_of(level, weights))
    out = out.withColumns({"cap_before": F.coalesce(F.sum("cap").over(before), F.lit(0)), "w_left": F.sum("w").over(by) - F.coalesce(F.sum("w").over(before), F.lit(0))})
    out = out.withColumn("full", F.expr("CAST(cap AS DECIMAL(19,0)) * w_left <= CAST(w AS DECIMAL(19,0)) * greatest(given - cap_before, 0)"))
    # from the first child that is not full on, the level stays
    out = out.withColumn("open", F.min(F.when(~F.col("full"), F.struct("cap_before", "w_left"))).over(by))
    share = F.expr("CAST(w AS DECIMAL(19,0)) * greatest(given - open.cap_before, 0) DIV open.w_left")
    return out.select(*parents, level, F.when(F.col("full"), F.col("cap")).otherwise(share).alias("budget"))


def select_prefixes(docs: DataFrame, share: tuple[int, int] = (3, 5), max_epochs: int = 2, weights: dict | None = None, seed: str = SEED, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """``doc_id, domain, lang, source, tokens, content, epochs`` of the documents (doc_id, text, lang, source) that the mix takes.

    A leaf gives whole epochs while its budget covers them, then the prefix of one more epoch, in that epoch's own seeded
    order, that does not exceed the rest. ``epochs`` is how often the document is taken. Running sums go over the 256
    buckets of a leaf by the order hash, over the 256 inside each of these, and so on, as deep as the largest leaf asks
    for, then inside a bucket: no window sees more rows than that or much more than ``bucket_rows`` documents. Null names are the empty name, null text has no
    tokens, rows that repeat an id and text are documents of their own, a null id is ordered as an empty one; extra
    columns are ignored; no rows give no rows.
    """
    rows = written(leaves(docs), "mix")
    sizes = written(rows.groupBy(*LEVELS).agg(F.sum("tokens").alias("available"), F.count(F.lit(1)).alias("n")), "leaves")
    depth, most = 1, sizes.agg(F.max("n")).first()[0] or 0
    while most > bucket_rows * 16 ** (DIGITS * depth):
        depth += 1
    plan = budgets(sizes.drop("n"), share, max_epochs, weights)
    plan = plan.withColumn("whole", F.expr("CASE WHEN available = 0 THEN 0L ELSE budget DIV available END")).withColumn("rest", F.col("budget") - F.col("whole") * F.col("available"))
    rows = rows.join(plan.select(*LEVELS, "whole", "rest"), list(LEVELS))
    rows = rows.withColumn("h", F.md5(F.concat_ws("|", F.lit(seed), F.col("whole").cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))))
    # one key for leaf and bucket: by the leaf's own columns Spark would deal whole leaves
    slot = lambda digits: F.to_json(F.struct(*LEVELS, F.substring("h", 1, digits).alias("bucket")))
    rows = rows.withColumn("slot", slot(DIGITS * depth))
    sums = written(rows.groupBy("slot").agg(F.sum("tokens").alias("s"), F.min("h").alias("h"), *[F.first(c).alias(c) for c in LEVELS]), "slots")
    before = None
    for level in range(1, depth + 1):
        parent = sums.select("*", slot(DIGITS * (level - 1)).alias("parent"), slot(DIGITS * level).alias("here"))
        here = parent.groupBy("parent", "here").agg(F.sum("s").alias("s"), F.min("h").alias("h"))
        earlier = Window.partitionBy("parent").orderBy("h").rowsBetween(Window.unboundedPreceding, -1)
        here = here.select("parent", "here", F.coalesce(F.sum("s").over(earlier), F.lit(0)).alias("b"))
        if before is not None:
            here = here.join(before.withColumnsRenamed({"here": "parent", "b": "a"}), "parent").select("here", (F.col("a") + F.col("b")).alias("b"))
        before = here.select("here", "b")
    sums = before.withColumnsRenamed({"here": "slot", "b": "before"})
    inside = Window.partitionBy("slot").orderBy("h", "content").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.join(sums, "slot")
    upto = F.col("before") + F.sum("tokens").over(inside)
    rows = rows.withColumn("epochs", F.col("whole") + F.when(upto <= F.col("rest"), 1).otherwise(0))
    return rows.where(F.col("epochs") > 0).select("doc_id", *LEVELS, "tokens", "content", "epochs")


def mixed(docs: DataFrame, share: tuple[int, int] = (4, 5), weights: dict | None = None, seed: str = SEED) -> DataFrame:
    """The rows of ``docs``, all columns, that a mix without repetition takes.

    Rows that repeat an id and text are taken together. A null text is an empty one without tokens, null names are the
    empty name, a null id is an id; extra columns stay, whatever they are called; no rows give no rows.
    """
    d, c = unused("_d", docs), unused("_c", docs)
    taken = select_prefixes(docs, share, 1, weights, seed).select(F.col("doc_id").alias(d), F.col("content").alias(c))
    return docs.join(taken, F.col("doc_id").eqNullSafe(F.col(d)) & (F.md5(text_or_empty()) == F.col(c)), "left_semi")
