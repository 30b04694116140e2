"""Token-ID output: ORC files in document order, with run-length encoded ids, row indexes and Bloom filters on ids."""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphrefresh.llm.bpe import TOKENIZER, encoder
from graphrefresh.llm.common import shuffle_partitions, text_or_empty, written

#: Bytes of text that a file and its task hold.
FILE_BYTES = 64 << 20
SCHEMA = "doc_id long, seq long, ids array<int>"
#: Every file has its rows in order, so a stripe or row group whose id range or Bloom filter excludes an id is skipped.
ORC = {"orc.stripe.size": str(16 << 20), "orc.row.index.stride": "1000", "orc.create.index": "true", "orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "compression": "zstd"}


def write_tokens(docs: DataFrame, path: str, tokenizer: str = TOKENIZER, end_id: int = 0, file_bytes: int = FILE_BYTES) -> None:
    """Write ``doc_id, seq, ids`` of every row of ``docs`` (doc_id, text) to ORC files under ``path``, in ascending doc_id order over the files' names.

    ``ids`` are the tokens of the whole text and then ``end_id``; ``seq`` is the row's place in its file. A file holds
    about ``file_bytes`` of text, however many there are. A null or empty text is its end id alone; null doc_ids come
    first; rows with one doc_id follow each other, over several files if need be, in order of a hash of their texts, then
    of the texts. Extra columns are ignored; no rows give files without rows. Only texts are shuffled, never ids.
    """
    text = text_or_empty()
    size = docs.agg(F.sum(F.octet_length(text))).first()[0] or 0
    n = max(shuffle_partitions(docs.sparkSession), -(-size // file_bytes))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("h"))
    placed = texts.repartitionByRange(n, "doc_id", "h").sortWithinPartitions("doc_id", "h", "text").drop("h")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        encode, seq, end = encoder(tokenizer).encode, 0, np.array([end_id], "<u4").tobytes()
        for b in batches:
            for i in range(0, b.num_rows, 2000):
                part = b.slice(i, 2000)
                ids = [x + end for x in encode(part.column(1).to_pylist())]
                offsets = np.zeros(len(ids) + 1, "i4")
                np.cumsum([len(x) // 4 for x in ids], out=offsets[1:])
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.Array.from_buffers(pa.int32(), int(offsets[-1]), [None, pa.py_buffer(b"".join(ids))]))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.arange(seq, seq + len(ids))), lists], ["doc_id", "seq", "ids"])
                seq += len(ids)

    placed.mapInArrow(run, SCHEMA).write.options(**ORC).orc(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """The files' rows; a filter on doc_id is pushed down to the stripes' indexes and Bloom filters, and stripes are read in parallel."""
    return spark.read.schema(SCHEMA).orc(path)


def summary(spark: SparkSession, path: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every row, from the files alone.

    Starts are running sums inside a file, after the sum of the files before it: only one row per file meets in one task.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            lists = b.column(2)
            offsets = np.asarray(lists.offsets)
            view = memoryview(np.ascontiguousarray(lists.values.to_numpy(zero_copy_only=False), "<i4")).cast("B")
            crc = [zlib.crc32(view[4 * a : 4 * z]) for a, z in zip(offsets, offsets[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.diff(offsets).astype("i8")), pa.array(crc, pa.int64()), b.column(3)], ["doc_id", "seq", "n_tokens", "ids_crc32", "file"])

    rows = read_tokens(spark, path).withColumn("file", F.regexp_extract(F.input_file_name(), r"(part-\d+)[^/]*$", 1))
    rows = written(rows.mapInArrow(run, "doc_id long, seq long, n_tokens long, ids_crc32 long, file string"), "token-rows")
    files = rows.groupBy("file").agg(F.sum("n_tokens").alias("total"))
    before = F.coalesce(F.sum("total").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rows = rows.join(files.select(F.col("file").alias("f"), before.alias("before")), F.col("file") == F.col("f"))
    inside = F.coalesce(F.sum("n_tokens").over(Window.partitionBy("file").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.select("doc_id", (F.col("before") + inside).alias("start"), "n_tokens", "ids_crc32")
