"""Things that several operators of the subpackage share: folders, null-safe inputs, Arrow batches."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..storage import new_path

ARROW_BYTES = 16 << 20


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write df as Parquet in the shared folder and read it back."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def modest_batches(df: DataFrame) -> None:
    """Batches of at most ARROW_BYTES on their way to Python (a session's smaller bound stays): long texts, little memory."""
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    now = re.sub(r"\D", "", conf.get(key))
    if not now or int(now) > ARROW_BYTES or int(now) <= 0:
        conf.set(key, str(ARROW_BYTES))


def texts(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id as long and text (null: empty) of a documents table, with nothing else but the columns named."""
    modest_batches(docs)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"), *more)


#: What to call to let go of what a worker process remembers between tasks.
CACHES: list = []
_last: list[str] = [""]


def trim() -> None:
    """What this worker process has freed goes back to the system: it may sit idle while others need the memory."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def enter(operator: str) -> None:
    """Called by an operator's Python code: what another operator left in this (reused) worker process is let go."""
    if _last[0] != operator:
        _last[0] = operator
        for clear in CACHES:
            clear()
        trim()


def laid(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string or binary column's values end to end (nulls: empty), and where each begins, and the end."""
    if column.null_count:
        column = pa.compute.fill_null(column, b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, places, values = column.buffers()
    if not len(column) or places is None:
        return np.empty(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    bounds = np.frombuffer(places, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(values, np.uint8)[bounds[0] : bounds[-1]] if values is not None else np.empty(0, np.uint8)
    return data, bounds - bounds[0]


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", most: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about `most` bytes of text (a longer text: alone), which bounds a worker's memory."""
    for batch in batches:
        if not batch.num_rows:
            continue
        column = batch.column(batch.schema.get_field_index(text))
        part = np.cumsum(pa.compute.fill_null(pa.compute.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)) // most
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if b > a:
                yield batch.slice(a, b - a)


def record(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def held_out(doc_id) -> F.Column:
    """Rows that no classifier learns from: crc32 of the doc_id as text is 2 modulo 4."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def smallest(rows: DataFrame, key: str, n: int, buckets: int = 64) -> DataFrame:
    """Of each `key` the n rows (key, doc_id; all distinct) with the smallest hash of doc_id, numbered from 1 as _k.

    Rows are first thinned in `buckets` by another hash, to twice their share of n and some: a key that holds most of
    all rows is spread over tasks, and the one that orders what is left of it reads a few times n rows at any size. (That
    a bucket holds more of the n smallest than it may keep is all but impossible; it would only change the choice.)
    """
    most = 2 * -(-n // buckets) + 16
    place = F.shiftrightunsigned(F.xxhash64("doc_id"), 11)
    dealt = rows.withColumn("_b", F.pmod(F.xxhash64("doc_id", F.lit("bucket")), F.lit(buckets)))
    each = dealt.withColumn("_r", F.row_number().over(W.partitionBy(key, "_b").orderBy(place, "doc_id"))).where(F.col("_r") <= most).drop("_b", "_r")
    return each.withColumn("_k", F.row_number().over(W.partitionBy(key).orderBy(place, "doc_id"))).where(F.col("_k") <= n)


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices of the concatenated runs [start, start + length)."""
    total = int(lengths.sum())
    if not total:
        return np.empty(0, np.int64)
    ends = np.cumsum(lengths)
    return np.arange(total, dtype=np.int64) + np.repeat(starts - (ends - lengths), lengths)
