"""Token counts: an exact histogram of encoded lengths whose suffix sums answer every context limit."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphrefresh.llm.bpe import TOKENIZER, encoder
from graphrefresh.llm.common import text_or_empty


def encoded_lengths(docs: DataFrame, tokenizer: str = TOKENIZER) -> DataFrame:
    """``length, n_docs`` summed up within a batch: a row per batch and length, not per document."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        encode = encoder(tokenizer).encode
        for b in batches:
            for i in range(0, b.num_rows, 1000):
                lengths, n = np.unique([len(x) // 4 for x in encode(b.column(0).slice(i, 1000).to_pylist())], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(lengths, pa.int64()), pa.array(n, pa.int64())], ["length", "n_docs"])

    return docs.select(text_or_empty().alias("text")).mapInArrow(run, "length long, n_docs long")


def histogram(docs: DataFrame, tokenizer: str = TOKENIZER) -> DataFrame:
    """One row per encoded length that occurs, with suffix sums over all longer documents.

    ``length, n_docs, n_tokens`` (of that length), ``docs_ge, tokens_ge`` (of that length or more), ``truncated_tokens``
    (all tokens left when every document is cut at that length), ``total_docs, total_tokens``. A null or empty text has
    length 0; ids and other columns play no part, repeated rows count each time; no rows give no rows. The windows run
    over the histogram, which has no more rows than the longest document has tokens, whatever the number of documents.
    """
    rows = encoded_lengths(docs, tokenizer).groupBy("length").agg(F.sum("n_docs").alias("n_docs"))
    rows = rows.withColumn("n_tokens", F.col("length") * F.col("n_docs"))
    after = Window.orderBy(F.desc("length")).rowsBetween(Window.unboundedPreceding, 0)
    out = rows.withColumns({"docs_ge": F.sum("n_docs").over(after), "tokens_ge": F.sum("n_tokens").over(after)})
    every = Window.orderBy(F.desc("length")).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    out = out.withColumns({"total_docs": F.sum("n_docs").over(every), "total_tokens": F.sum("n_tokens").over(every)})
    cut = F.col("total_tokens") - F.col("tokens_ge") + F.col("length") * F.col("docs_ge")
    return out.withColumn("truncated_tokens", cut).select("length", "n_docs", "n_tokens", "docs_ge", "tokens_ge", "truncated_tokens", "total_docs", "total_tokens")


def at_limits(hist: DataFrame, limits: list[int]) -> DataFrame:
    """``context_limit, truncated_tokens, docs_cut``: what a cut at any limit keeps, from the first longer length's suffix sums."""
    asked = hist.sparkSession.createDataFrame([(int(x),) for x in limits], "context_limit long")
    longer = F.col("length") > F.col("context_limit")
    ge = lambda c: F.coalesce(F.max(F.when(longer, F.col(c))), F.lit(0))
    out = hist.join(F.broadcast(asked)).groupBy("context_limit").agg(F.max("total_tokens").alias("t"), ge("tokens_ge").alias("tg"), ge("docs_ge").alias("docs_cut"))
    return out.select("context_limit", (F.col("t") - F.col("tg") + F.col("context_limit") * F.col("docs_cut")).alias("truncated_tokens"), "docs_cut")


def quantile(hist: DataFrame, q: float) -> Column | int | None:
    """The smallest length that at least a share ``q`` of the documents doesn't exceed; None for no documents."""
    upto = F.col("total_docs") - F.col("docs_ge") + F.col("n_docs")
    return hist.where(upto >= q * F.col("total_docs")).agg(F.min("length")).first()[0]
