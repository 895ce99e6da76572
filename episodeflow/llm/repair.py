"""Token-id output compressed by grammar: frequent id pairs become nonterminals, shard by shard.

A shard holds the ids of consecutive documents in ascending doc_id order. Its bytes are, little-endian:
magic `PAIR`, version, counts (rules, sequence, documents, tokens), the first nonterminal, the rules (two ids each),
the rules' expansion lengths, the sequence, the documents' ids and lengths, a bit for each doc_id that is null. Rule r is nonterminal `first + r`; a rule
names earlier symbols only. Expansion lengths make any token reachable without decoding what stands before it.

Rounds stand in for the one-pair-at-a-time loop: each takes the most frequent pairs, one for `ROUND` ids of the shard,
replaces them from left to right, and leaves overlapping pairs to the next round. Rounds go on until no pair is left that
is found `min_pair` times; a rule takes three integers of the shard, so that a rarer pair would not pay for its rule.

Null texts are empty; empty tables give no shard; a doc_id that repeats keeps all its rows; a null doc_id comes first.
Columns besides doc_id and text aren't read, so their names can't clash.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import new_path
from .common import enter, laid, ragged, record, slices, texts
from .tokens import encoder

HEAD = struct.Struct("<4sIIIIII")
MAGIC, VERSION = b"PAIR", 2
SHARD_TOKENS = 1 << 20
ROUND, MIN_PAIR = 256, 4
BITS = 20


def _slots(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A hash of BITS bits for each pair."""
    return (a * np.uint32(2654435761) + b * np.uint32(2246822519)) >> np.uint32(32 - BITS)


def _frequent(seq: np.ndarray, places: np.ndarray, most: int, min_pair: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The `most` most frequent pairs among places (more where they tie), first << 32 | second; where one stands; which one;
    and the places of all pairs found `min_pair` times (a few rarer ones among them).

    Of pairs that share a slot of the table the last one is taken, the others wait for another round.
    """
    a, b = seq[places], seq[places + 1]
    keys = (a.astype(np.int64) << 32) | b
    order = np.sort(keys)
    opens = np.flatnonzero(np.append(True, order[1:] != order[:-1])) if len(order) else np.empty(0, np.int64)
    counts = np.diff(opens, append=len(order))
    opens, counts = opens[counts >= min_pair], counts[counts >= min_pair]
    often = np.zeros(1 << BITS, bool)
    often[_slots((order[opens] >> 32).astype(np.uint32), order[opens].astype(np.uint32))] = True
    if len(counts) > most:
        opens = opens[counts >= np.partition(counts, -most)[-most]]
    found = order[opens]
    number = np.full(1 << BITS, -1, np.int32)
    number[_slots((found >> 32).astype(np.uint32), found.astype(np.uint32))] = np.arange(len(found))
    slots = _slots(a, b)
    live = np.flatnonzero(often[slots])
    rule = number[slots[live]]
    taken = np.flatnonzero(rule >= 0)
    rule, at = rule[taken], live[taken]
    fits = found[rule] == keys[at]
    return found, places[at[fits]], rule[fits], places[live]


def compress(ids: np.ndarray, first: int, every: int = ROUND, min_pair: int = MIN_PAIR) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rules (two columns), their expansion lengths, and the sequence. Symbols below `first` are ids.

    After a round only pairs that hold one of its nonterminals, or were frequent before it, can be frequent: the next
    round looks at their places alone, and finds what it would find among all.
    """
    seq = ids.astype(np.uint32)
    rules, lengths = [np.empty((0, 2), np.uint32)], [np.empty(0, np.uint32)]
    most, made, size = max(16, len(seq) // every), 0, np.ones(first, np.uint32)
    places = np.arange(max(0, len(seq) - 1))
    while len(places):
        found, hits, rule, places = _frequent(seq, places, most, min_pair)
        if not len(found):
            break
        opens = np.flatnonzero(np.diff(hits, prepend=-2) != 1)  # of runs of overlapping hits every second one counts
        inside = np.arange(len(hits)) - np.repeat(opens, np.diff(opens, append=len(hits)))
        hits, rule = hits[inside % 2 == 0], rule[inside % 2 == 0]
        used = np.zeros(len(found), bool)
        used[rule] = True  # a pair may have lost all its places to others
        rule, found = (np.cumsum(used) - 1)[rule], found[used]
        pair = np.stack([found >> 32, found & 0xFFFFFFFF], axis=1).astype(np.uint32)
        seq[hits] = (first + made + rule).astype(np.uint32)
        stays = np.ones(len(seq), bool)
        stays[hits + 1] = False
        look = np.zeros(len(seq), bool)
        look[places] = True
        look[hits] = True
        before = hits[hits > 0] - 1
        look[before - ~stays[before]] = True  # the place before, or that of the nonterminal which took it
        seq, look = seq[stays], look[stays]
        places = np.flatnonzero(look[:-1])
        rules.append(pair)
        lengths.append(size[pair[:, 0]] + size[pair[:, 1]])
        size = np.concatenate([size, lengths[-1]])
        made += len(found)
    return np.concatenate(rules), np.concatenate(lengths), seq


def pack(doc_ids: list, lengths: np.ndarray, ids: np.ndarray) -> bytes:
    first = int(ids.max()) + 1 if len(ids) else 1
    rules, spans, seq = compress(ids, first)
    null = np.packbits(np.array([d is None for d in doc_ids], bool))
    docs = np.array([0 if d is None else d for d in doc_ids], "<i8")
    return HEAD.pack(MAGIC, VERSION, len(rules), len(seq), len(docs), len(ids), first) + b"".join(x.astype(t).tobytes() for x, t in ((rules, "<u4"), (spans, "<u4"), (seq, "<u4"), (docs, "<i8"), (lengths, "<u4"), (null, "u1")))


class Shard:
    """A packed shard opened for reading."""

    def __init__(self, data: bytes):
        magic, version, n_rules, n_seq, n_docs, self.n_tokens, self.first = HEAD.unpack_from(data)
        if magic != MAGIC or version != VERSION:
            raise ValueError("not a shard of this format")
        at = HEAD.size

        def take(n: int, kind: str) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(data, kind, n, at)
            at += out.nbytes
            return out

        self.rules = take(2 * n_rules, "<u4").reshape(-1, 2)
        self.spans, self.seq, self.docs, self.lengths = take(n_rules, "<u4"), take(n_seq, "<u4"), take(n_docs, "<i8"), take(n_docs, "<u4")
        self.null = np.unpackbits(take(-(-n_docs // 8), "u1"), count=n_docs).astype(bool)
        self.starts = np.cumsum(self.lengths, dtype=np.int64) - self.lengths
        self._ends = None

    def _expand(self, symbols: np.ndarray) -> np.ndarray:
        """All symbols written out, every round one rule deeper where a rule still stands."""
        out = symbols.astype(np.int64)
        while len(deep := np.flatnonzero(out >= self.first)):
            step = np.ones(len(out), np.int64)
            step[deep] = 2
            at = np.cumsum(step) - step
            new = np.repeat(out, step)
            pair = self.rules[out[deep] - self.first]
            new[at[deep]], new[at[deep] + 1] = pair[:, 0], pair[:, 1]
            out = new
        return out.astype(np.uint32)

    def decode(self) -> np.ndarray:
        """Every rule is written out once; the sequence then gathers whole expansions."""
        if not len(self.rules):
            return np.asarray(self.seq, np.uint32)
        flat = self._expand(np.arange(self.first, self.first + len(self.rules), dtype=np.int64))
        begin = np.cumsum(self.spans, dtype=np.int64) - self.spans
        seq = self.seq.astype(np.int64)
        is_rule = seq >= self.first
        table = np.concatenate([flat, seq[~is_rule].astype(np.uint32)])
        starts, lengths = np.empty(len(seq), np.int64), np.ones(len(seq), np.int64)
        starts[is_rule], lengths[is_rule] = begin[seq[is_rule] - self.first], self.spans[seq[is_rule] - self.first]
        starts[~is_rule] = len(flat) + np.arange(int((~is_rule).sum()))
        return table[ragged(starts, lengths)]

    def slice(self, start: int, length: int) -> np.ndarray:
        """Tokens [start, start + length) of the shard, expanding only the symbols that hold them."""
        if self._ends is None:
            seq = self.seq.astype(np.int64)
            size = np.ones(len(seq), np.int64)
            size[seq >= self.first] = self.spans[seq[seq >= self.first] - self.first]
            self._ends = np.cumsum(size)
        if length <= 0:
            return np.empty(0, np.uint32)
        a, b = np.searchsorted(self._ends, start, "right"), np.searchsorted(self._ends, start + length, "left") + 1
        skip = start - (self._ends[a - 1] if a else 0)
        return self._expand(self.seq[a:b])[skip : skip + length]

    def doc_ids(self) -> list:
        return [None if no else d for d, no in zip(self.docs.tolist(), self.null.tolist(), strict=True)]

    def document(self, k: int) -> np.ndarray:
        return self.slice(int(self.starts[k]), int(self.lengths[k]))


SHARDS = "part int, shard int, n_docs long, n_tokens long, payload binary"
ROWS = "part int, shard int, doc_id long, at long, n_tokens long, ids_crc32 long"


def write_shards(docs: DataFrame, path: str, tokenizer: str = "byte_bpe_50k.json", end_id: int = 0, parts: int | None = None, shard_tokens: int = SHARD_TOKENS) -> None:
    """Encode documents, range-partitioned by doc_id, and write one row for each shard (a longer document: a shard alone).

    Partitions are consecutive ranges of doc_id, `part` is their number; shards count up within a part.
    """
    schema = pa.schema([("part", pa.int32()), ("shard", pa.int32()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("payload", pa.binary())])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("ids")
        from pyspark import TaskContext

        part, enc, shard = TaskContext.get().partitionId(), encoder(tokenizer), 0
        names, lengths, arrays, held = [], [], [], 0

        def flush() -> pa.RecordBatch:
            nonlocal names, lengths, arrays, held, shard
            ids, sizes = np.concatenate(arrays), np.concatenate(lengths)
            out = record(schema, [part], [shard], [len(names)], [len(ids)], [pack(names, sizes.astype(np.uint32), ids)])
            names, lengths, arrays, held, shard = [], [], [], 0, shard + 1
            return out

        for batch in slices(batches, most=4 << 20):
            ids, sizes = enc.encode_bytes(*laid(batch.column(1)))
            sizes = sizes + 1
            ends = np.cumsum(sizes)
            whole = np.ones(len(ids) + len(sizes), bool)
            whole[ends - 1] = False
            tokens = np.full(len(whole), end_id, np.uint32)
            tokens[whole] = ids
            own, a = batch.column(0).to_pylist(), 0
            while a < len(own):
                begin = int(ends[a] - sizes[a])
                b = int(np.searchsorted(ends, begin + shard_tokens - held, "right"))
                if b == a and held:
                    yield flush()
                    continue
                b = max(b, a + 1)
                names += own[a:b]
                lengths.append(sizes[a:b])
                arrays.append(tokens[begin : int(ends[b - 1])])
                held += int(ends[b - 1]) - begin
                a = b
        if held:
            yield flush()

    rows = texts(docs).withColumn("_h", F.xxhash64("text"))  # so that a doc_id which repeats can be split
    n = parts or int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = [F.col("doc_id").asc_nulls_first(), F.col("_h").asc()]
    rows.repartitionByRange(n, *order).sortWithinPartitions(*order).select("doc_id", "text").mapInArrow(encode, SHARDS).write.parquet(path)


def read_shards(spark: SparkSession, path: str) -> DataFrame:
    """One row for each document of the shards at path: where it starts in its shard, its tokens and their crc32."""
    schema = pa.schema([("part", pa.int32()), ("shard", pa.int32()), ("doc_id", pa.int64()), ("at", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                part, shard, data = (batch.column(c)[k].as_py() for c in range(3))
                opened = Shard(data)
                ids = memoryview(opened.decode().astype("<u4")).cast("B")
                ends = 4 * (opened.starts + opened.lengths)
                crc = [zlib.crc32(ids[4 * a : b]) for a, b in zip(opened.starts.tolist(), ends.tolist(), strict=True)]
                n = len(crc)
                yield record(schema, [part] * n, [shard] * n, opened.doc_ids(), opened.starts, opened.lengths.astype(np.int64), crc)

    return spark.read.schema(SHARDS).parquet(path).select("part", "shard", "payload").mapInArrow(decode, ROWS)


def digest(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", end_id: int = 0) -> DataFrame:
    """Write the shards, read them back, and return doc_id, start, n_tokens, ids_crc32 of each document."""
    spark = docs.sparkSession
    path = new_path(spark, "pair-grammar")
    write_shards(docs, path, tokenizer, end_id)
    sizes = spark.read.schema(SHARDS).parquet(path).select("part", "shard", "n_tokens")
    # Offsets in two steps: shards within their part, then parts (as many rows as partitions) before one another.
    from pyspark.sql import Window as W

    shards = sizes.withColumn("before", F.sum("n_tokens").over(W.partitionBy("part").orderBy("shard").rowsBetween(W.unboundedPreceding, -1)))
    parts = sizes.groupBy("part").agg(F.sum("n_tokens").alias("tokens"))
    base = parts.select("part", F.sum("tokens").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)).alias("base"))
    offsets = shards.join(base, "part").select("part", "shard", (F.coalesce("base", F.lit(0)) + F.coalesce("before", F.lit(0))).alias("shard_start"))
    return read_shards(spark, path).join(offsets, ["part", "shard"]).select("doc_id", (F.col("shard_start") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")
