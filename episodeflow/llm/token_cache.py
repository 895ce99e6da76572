"""Token counts through a digest cache: what has been counted once, under any doc_id and in any run, isn't encoded again.

A row of the cache is (content digest, tokenizer digest, n_tokens). The content digest is SHA-256 of the normalised
text; only null is normalised (to empty), since any other change may change the count. The tokenizer digest covers the
vocabulary file and the library's version. Documents are joined to the cache by digest; digests without a count are
the misses. A map task hands on each missing text once (compressed), tasks that share a digest meet in a shuffle, and
one of them is encoded. New counts are appended to the cache.

Copies cost a digest each, and a text with a third of all rows is handed on by each task once. Null and empty texts
have no tokens; repeated rows keep their rows; empty tables give no rows; other columns aren't read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import new_path
from .common import enter, materialise, record, slices, texts
from .tokens import encoder

CACHE = "digest binary, tokenizer string, n_tokens long"
SEEN = 200_000
ENCODE_BYTES = 2 << 20


def tokenizer_digest(name: str) -> str:
    """Of the vocabulary file and the version of the library that reads it."""
    import os

    import sentencepiece
    import tokenizers

    path = name if os.path.exists(name) else public_tokenizers.path(name)
    version = sentencepiece.__version__ if path.endswith(".model") else tokenizers.__version__
    with open(path, "rb") as f:
        return hashlib.sha256(f.read() + version.encode()).hexdigest()


_models: dict = {}


def count_tokens(name: str, raw: list[bytes]) -> list[int]:
    """How many tokens each text (UTF-8) has."""
    if name.endswith(".model"):
        import sentencepiece

        if name not in _models:
            import os

            _models[name] = sentencepiece.SentencePieceProcessor(model_file=name if os.path.exists(name) else public_tokenizers.path(name))
        return [len(ids) for ids in _models[name].encode([t.decode("utf-8", "surrogatepass") for t in raw], num_threads=1)] if raw else []
    return encoder(name).encode_bytes(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]), only_lengths=True)[1].tolist()


def _once(docs: DataFrame) -> DataFrame:
    """(digest, packed): each task's distinct texts, as far as it remembers the last `SEEN` digests."""
    schema = pa.schema([("digest", pa.binary()), ("packed", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("ids")
        seen: set[bytes] = set()
        press = zstandard.ZstdCompressor(level=1)
        for batch in slices(batches):
            keys, packed = [], []
            for d, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if d not in seen:
                    if len(seen) >= SEEN:
                        seen.clear()
                    seen.add(d)
                    keys.append(d)
                    packed.append(press.compress(t.encode("utf-8", "surrogatepass")))
            yield record(schema, keys, packed)

    return docs.mapInArrow(run, "digest binary, packed binary")


def _encoded(packed: DataFrame, tokenizer: str) -> DataFrame:
    """One row for each digest; rows of a digest come one after the other."""
    schema = pa.schema([("digest", pa.binary()), ("n_tokens", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("ids")
        last, open_ = None, zstandard.ZstdDecompressor()
        for batch in batches:
            keys, rows = [], []
            for d, p in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if d != last:
                    keys.append(d)
                    rows.append(p)
                    last = d
            counts, held, size = [], [], 0
            for p in rows:
                held.append(open_.decompress(p.as_py()))
                size += len(held[-1])
                if size >= ENCODE_BYTES:
                    counts += count_tokens(tokenizer, held)
                    held, size = [], 0
            counts += count_tokens(tokenizer, held)
            yield record(schema, keys, np.array(counts, np.int64))

    n = int(packed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return packed.repartition(n, "digest").sortWithinPartitions("digest").mapInArrow(run, "digest binary, n_tokens long")


def open_cache(spark: SparkSession, path: str) -> DataFrame:
    """The cache at path; empty where there is none yet."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    there = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)
    return spark.read.schema(CACHE).parquet(path) if there else spark.createDataFrame([], CACHE)


def token_counts(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", cache: str | None = None, limit: int = 512) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit); new counts are appended to the cache (none named: a new one)."""
    spark = docs.sparkSession
    path = cache or new_path(spark, "token-cache")
    version = tokenizer_digest(tokenizer)
    rows = texts(docs).withColumn("digest", F.unhex(F.sha2(F.col("text").cast("binary"), 256)))
    known = open_cache(spark, path).where(F.col("tokenizer") == version).groupBy("digest").agg(F.max("n_tokens").alias("n_tokens"))
    there = known.limit(1).count()
    missing = rows.select("digest", "text")
    if there:
        missing = missing.join(known.select("digest"), "digest", "left_anti")
    new = _encoded(_once(missing), tokenizer).select("digest", F.lit(version).alias("tokenizer"), "n_tokens")
    new.write.mode("append").parquet(path)
    counted = spark.read.schema(CACHE).parquet(path).where(F.col("tokenizer") == version).groupBy("digest").agg(F.max("n_tokens").alias("n_tokens"))
    counted = materialise(counted, "token-counts")  # an aggregate right below the join would keep Spark from splitting a hot digest
    sized = rows.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), "digest")
    return sized.join(counted, "digest").select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
