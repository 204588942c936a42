"""Token ids in Parquet list columns, ordered by document.

Layout: files are numbered in ascending doc_id order and sorted inside; each row holds doc_id,
n_tokens and the list of ids. Ids are delta-packed in version 2 pages (no dictionary, which
would overflow on ids), the other columns as well; row groups and pages are kept small, and
the writer adds column and offset indexes. So a range of documents, or the counts alone, can
be read without touching the other pages.

Defined cases: null or empty text gives just the end id; equal doc_ids are ordered by a hash of their text;
repeated rows each get their own list; an empty table gives no row; further columns of the
input are not written.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import tokens
from .common import documents, fresh_path, id_text, sliced

WRITER = {"compression": "zstd", "parquet.writer.version": "v2", "parquet.enable.dictionary": "false", "parquet.block.size": str(32 << 20), "parquet.page.size": str(256 << 10), "parquet.page.row.count.limit": "2000"}
#: Up to this many files their totals are broadcast (some 50 bytes each), beyond it they are shuffled.
BROADCAST_FILES = 100_000
#: Characters of text for one file: it bounds what one task sorts, encodes and later sums.
FILE_CHARS = 64_000_000
SCHEMA = "doc_id bigint, n_tokens bigint, ids array<int>"


def encode_rows(docs: DataFrame, end_id: int, file: str = tokens.DEFAULT_FILE) -> DataFrame:
    def run(batches):
        encoder = tokens.encoder(file)
        for b in sliced(batches):
            ids, offsets = encoder.encode_array(b.column(1), end_id)
            lists = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(ids.view("<i4")))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.diff(offsets)), lists], names=["doc_id", "n_tokens", "ids"])

    return docs.mapInArrow(run, SCHEMA)


def files_of(docs: DataFrame) -> int:
    """As many files as there are FILE_CHARS of text, and some per core at least."""
    chars = docs.agg(F.sum(F.length("text"))).first()[0] or 0
    return max(2 * docs.sparkSession.sparkContext.defaultParallelism, -(-chars // FILE_CHARS))


def write_tokens(docs: DataFrame, path: str, end_id: int = 0, file: str = tokens.DEFAULT_FILE, partitions: int | None = None) -> None:
    """Texts are dealt out by ranges of doc_id (and a hash of the text, so that one id can't fill a range) before they are encoded."""
    keys = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text")]
    rows = id_text(docs)
    ranged = rows.repartitionByRange(partitions or files_of(rows), *keys)
    encode_rows(ranged.sortWithinPartitions(*keys), end_id, file).write.options(**WRITER).parquet(path)


def read_metadata(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, n_tokens and the place in the corpus, without reading any id."""
    return placed(spark.read.schema(SCHEMA).parquet(path).select("doc_id", "n_tokens", *_place()))


def read_tokens(spark: SparkSession, path: str, low: int | None = None, high: int | None = None) -> DataFrame:
    """The lists of the documents with low <= doc_id <= high; statistics and page indexes skip the rest."""
    df = spark.read.schema(SCHEMA).parquet(path)
    if low is not None:
        df = df.filter(F.col("doc_id") >= low)
    return df if high is None else df.filter(F.col("doc_id") <= high)


def _place():
    return F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("row")


def placed(rows: DataFrame, sizes: DataFrame | None = None) -> DataFrame:
    """Adds start: sums inside each file, which holds a bounded range, after the totals of the files before it (one small
    row a file). sizes: file and n_tokens, where they are cheaper to read than rows."""
    number = F.regexp_extract("file", r"part-(\d+)", 1).cast("bigint")
    totals = (rows if sizes is None else sizes).groupBy("file").agg(F.sum("n_tokens").alias("total"))
    before = totals.select("file", (F.sum("total").over(Window.orderBy(number)) - F.col("total")).alias("before"))
    small = len(rows.inputFiles()) <= BROADCAST_FILES
    inside = F.sum("n_tokens").over(Window.partitionBy("file").orderBy("row")) - F.col("n_tokens")
    return rows.withColumn("inside", inside).join(F.broadcast(before) if small else before, "file").withColumn("start", F.col("before") + F.col("inside")).drop("before", "inside", "file", "row")


def checksums(stored: DataFrame) -> DataFrame:
    """Reads every list and gives its length and CRC."""

    def run(batches):
        from zlib import crc32

        for b in batches:
            lists = b.column(b.schema.get_field_index("ids"))
            offsets, raw = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False).astype("<u4").tobytes()
            spans = list(zip(offsets.tolist(), offsets[1:].tolist()))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i, n in enumerate(b.schema.names) if n != "ids"), pa.array([e - s for s, e in spans], pa.int64()), pa.array([crc32(raw[4 * s : 4 * e]) for s, e in spans], pa.int64())], names=[*(n for n in b.schema.names if n != "ids"), "n_tokens", "ids_crc32"])

    return stored.select("doc_id", *_place(), "ids").mapInArrow(run, "doc_id bigint, file string, row bigint, n_tokens bigint, ids_crc32 bigint")


def op5(spark, sf_dir) -> DataFrame:
    path = fresh_path(spark, "tokens")
    write_tokens(documents(spark, sf_dir), path, end_id=0)
    stored = spark.read.schema(SCHEMA).parquet(path)
    return placed(checksums(stored), stored.select("n_tokens", _place()[0])).select("doc_id", "start", "n_tokens", "ids_crc32")
