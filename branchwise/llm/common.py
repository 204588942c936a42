"""Shared pieces: tables, words, work folders and per-worker caches."""

from __future__ import annotations

import re
import sys
import tempfile
import types
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a longest run of characters other than the space and the controls 9 to 13.
WORD = r"[^\x20\x09-\x0D]+"
WORD_RE = re.compile(WORD)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def work_dir(spark: SparkSession) -> str:
    """The folder all machines share. A folder of this machine only where the session names none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        found = spark.sparkContext.getCheckpointDir()
        named = found or f"file://{tempfile.mkdtemp(prefix='branchwise-')}"
        if not found:
            spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


#: One name for everything a driver process settles, so that runs do not meet each other.
_RUN = uuid.uuid4().hex
#: Rows of a small table that one file holds.
ROWS_A_FILE = 1_000_000
#: A broadcast side has at most this many rows, by construction or by a count.
FEW = 2_000


def _filesystem(spark: SparkSession, path: str):
    """The Hadoop path and its file system."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark._jsc.hadoopConfiguration())


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; what is left there when the driver ends is deleted then."""
    run = f"{work_dir(spark)}/branchwise/{_RUN}"
    at, fs = _filesystem(spark, run)
    if fs.mkdirs(at):
        fs.deleteOnExit(at)
    return f"{run}/{name}-{uuid.uuid4().hex}"


def compact(df: DataFrame, rows: int = 0) -> DataFrame:
    """Shuffled results of so many narrow rows in four files per core, or one per ROWS_A_FILE rows where that is more.
    Not for plans that end in work on texts: joining partitions would join their tasks."""
    return df.coalesce(max(4 * df.sparkSession.sparkContext.defaultParallelism, rows // ROWS_A_FILE))


def settled(df: DataFrame, name: str, rows: int | None = None, **options: str) -> DataFrame:
    """Write once to the shared folder and read back: later steps no longer depend on the executors that made it.
    rows: in few files, by ``compact``; 0 for tables bounded by the model. Else each task writes its file. options: of the writer."""
    path = fresh_path(df.sparkSession, name)
    (df if rows is None else compact(df, rows)).write.options(**options).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._settled = path
    return out


def discard(df: DataFrame) -> None:
    """Delete a settled table that nothing will read again."""
    at, fs = _filesystem(df.sparkSession, df._settled)
    fs.delete(at, True)


@contextmanager
def rows_a_batch(spark: SparkSession, rows: int):
    """Jobs started inside hand so many rows at a time to Python: for large rows, of which a batch would else hold all of a task."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def hot_join(left: DataFrame, right: DataFrame, key: str, hot: DataFrame, how: str = "inner") -> DataFrame:
    """left joined to right (one row per key) where the keys in ``hot`` (key; at most FEW rows) may hold most rows of
    left: their rows meet a broadcast copy and are not moved, the others are shuffled."""
    hot = F.broadcast(hot.select(F.col(key).alias("_hot_key")))
    is_hot = F.col(key) == F.col("_hot_key")
    many = left.join(hot, is_hot, "left_semi").join(F.broadcast(right.join(hot, is_hot, "left_semi")), key, how)
    return left.join(hot, is_hot, "left_anti").join(right, key, how).unionByName(many)


def worker_cache(name: str) -> dict:
    """A dictionary that outlives one task in a reused Python worker. A new name drops the older ones, so operators don't add up."""
    box = sys.modules.setdefault("_branchwise_worker", types.ModuleType("_branchwise_worker"))
    if name not in box.__dict__:
        for other in [k for k, v in box.__dict__.items() if isinstance(v, dict) and k[:2] != "__"]:
            del box.__dict__[other]
    return box.__dict__.setdefault(name, {})


def columns(batch: pa.RecordBatch, *names: str) -> list[list]:
    return [batch.column(batch.schema.get_field_index(n)).to_pylist() for n in names]


def sliced(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = 4_000_000) -> Iterator[pa.RecordBatch]:
    """The same rows in slices of about ``most`` bytes of text, so that memory follows that and not the batch."""
    import pyarrow.compute as pc

    for b in batches:
        sizes = pc.fill_null(pc.binary_length(b.column(b.schema.get_field_index(column))), 0).to_pylist()
        start = size = 0
        for i, n in enumerate(sizes, 1):
            size += n
            if size >= most:
                yield b.slice(start, i - start)
                start, size = i, 0
        if start < len(sizes):
            yield b.slice(start)


def text_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, list[str]]]:
    """(doc_id, text) batches as lists; a null text counts as the empty one."""
    for b in sliced(batches):
        ids, texts = columns(b, "doc_id", "text")
        yield ids, [t or "" for t in texts]


def id_text(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))


def id_mod(column: str, n: int):
    """crc32 of the id as text, modulo n; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % n
