"""Documents packed into sequences: sizes grouped and rounded up, configurations optimised, small pieces fitted best.

Only the histogram of piece lengths (as many rows as the sequence is long) goes to the driver. There, lengths above
a share of the sequence are cut into groups of equal cardinality and rounded up to their group's largest; a linear
program over configurations of these few sizes is solved by generating columns; its whole part places actual pieces,
group by group, in runs of like sequences; what is left, then the small pieces, go longest first to the fullest run
that takes them. The plan says for each length which ranks go where, and documents find their place by their rank.

A document's tokens are its ids and the end id. Only longer ones are cut, so that all pieces but the first are full.
Null texts are empty (one token); empty tables give no rows; repeated rows are packed one by one; other columns aren't
read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from .common import enter, laid, materialise, record, slices, texts
from .tokens import MOST_PIECES, encoder

LIMIT = 1024
#: (share of the sequence up to which a piece is small, groups): the plan with the fewest sequences is taken.
SCHEMES = ((1 / 8, 40), (1 / 3, 80), (1 / 2, 256))


def configurations(sizes: np.ndarray, demand: np.ndarray, limit: int, steps: int = 400) -> tuple[np.ndarray, np.ndarray]:
    """Configurations (a row each: how many of each size) and how often each is used, at the optimum of the relaxation."""
    k = len(sizes)
    basis = np.diag((limit // sizes).astype(float))
    inverse = np.diag(1 / np.diag(basis))
    places = np.arange(limit + 1)[None, :] - sizes[:, None]
    fits = places >= 0
    places = np.maximum(places, 0)
    for step in range(steps):
        used = inverse @ demand
        price = np.maximum(inverse.sum(axis=0), 0)
        worth, picks = np.zeros(limit + 1), []
        for _ in range(limit // int(sizes.min())):  # the best of one more size at most
            values = np.where(fits, worth[places] + price[:, None], -1)
            pick = values.argmax(axis=0)
            more = values[pick, np.arange(limit + 1)]
            picks.append(np.where(more > worth + 1e-12, pick, -1))
            worth = np.maximum(worth, more)
        if worth[limit] <= 1 + 1e-9:
            break
        column, room = np.zeros(k), limit
        for pick in reversed(picks):
            if pick[room] >= 0:
                column[pick[room]] += 1
                room -= int(sizes[pick[room]])
        way = inverse @ column
        ratio = np.where(way > 1e-9, used / np.where(way > 1e-9, way, 1), np.inf)
        leaves = int(np.argmin(ratio))
        basis[:, leaves] = column
        if step % 40 == 39:  # anew, before errors add up
            inverse = np.linalg.inv(basis)
        else:
            row = inverse[leaves] / way[leaves]
            inverse = inverse - np.outer(way, row)
            inverse[leaves] = row
    return basis.T.round().astype(np.int64), np.maximum(inverse @ demand, 0)


class Plan:
    """rows: (length, first rank, pieces, first sequence, pieces of this row in each sequence, offset there)."""

    def __init__(self, counts: dict[int, int], limit: int = LIMIT, small: float = 1 / 8, groups: int = 64):
        self.limit, self.rows, self.sequences = limit, [], 0
        self.taken = dict.fromkeys(counts, 0)
        self.runs: dict[int, list[list[int]]] = {}  # by room: [first sequence, sequences]
        if counts.get(limit):
            self._place(limit, counts[limit], self._open(counts[limit]), 1, 0)
        counts = {n: c for n, c in counts.items() if n < limit and c}
        self._grouped({n: c for n, c in counts.items() if n > small * limit}, groups)
        for length in sorted(counts, reverse=True):
            self._fit(length, counts[length] - self.taken[length])

    def _open(self, n: int) -> int:
        self.sequences += n
        return self.sequences - n

    def _place(self, length: int, n: int, sequence: int, each: int, offset: int) -> None:
        self.rows.append((length, self.taken[length], n, sequence, each, offset))
        self.taken[length] += n

    def _room(self, room: int, first: int, n: int) -> None:
        if n and room:
            self.runs.setdefault(room, []).append([first, n])

    def _grouped(self, counts: dict[int, int], groups: int) -> None:
        if not counts:
            return
        lengths = np.array(sorted(counts, reverse=True))
        ends = np.cumsum([counts[n] for n in lengths.tolist()])
        total = int(ends[-1])
        edges = np.unique(np.linspace(0, total, min(groups, total) + 1).astype(np.int64))
        sizes = lengths[np.searchsorted(ends, edges[:-1], "right")]
        keep = np.concatenate([[True], np.diff(sizes) != 0])  # groups of one size are one
        edges, sizes = np.append(edges[:-1][keep], total), sizes[keep]
        rows, used = configurations(sizes, np.diff(edges).astype(float), self.limit)
        at = edges[:-1].copy()  # pieces in falling order: the next of each group
        for config, often in sorted(zip(rows.tolist(), np.floor(used + 1e-6).astype(int).tolist(), strict=True), reverse=True):
            slots = [g for g, c in enumerate(config) for _ in range(c)]
            if slots:
                often = min([often, *((edges[g + 1] - at[g]) // config[g] for g in set(slots))])
            if not slots or often <= 0:
                continue
            begin = []
            for g in slots:
                begin.append(int(at[g]))
                at[g] += often
            cuts = {0, int(often)}
            for b in begin:
                cuts.update((ends[(ends > b) & (ends < b + often)] - b).tolist())
            cuts, first = sorted(cuts), self._open(int(often))
            for a, z in zip(cuts, cuts[1:], strict=False):
                offset = 0
                for b in begin:
                    k = int(np.searchsorted(ends, b + a, "right"))
                    length = int(lengths[k])
                    self.rows.append((length, b + a - int(ends[k] - counts[length]), z - a, first + a, 1, offset))
                    offset += length
                self._room(self.limit - offset, first + a, z - a)
        # What the configurations leave of each group is its tail; move the tails of a length behind what is taken.
        self._renumber(lengths, counts)

    def _renumber(self, lengths: np.ndarray, counts: dict[int, int]) -> None:
        """Ranks of a length are handed out anew, gapless from 0, so that the rest of it is one range."""
        rows, self.rows = sorted(self.rows), []
        for length, _, n, sequence, each, offset in rows:
            if length not in counts:
                self.rows.append((length, _, n, sequence, each, offset))
            else:
                self._place(length, n, sequence, each, offset)

    def _fit(self, length: int, n: int) -> None:
        while n > 0:
            room = min((r for r in self.runs if r >= length), default=None)
            if room is None:
                each = self.limit // length
                opened = -(-n // each)
                self._room(self.limit, self._open(opened), opened)
                room = self.limit
            stack = self.runs[room]
            first, have = stack.pop()
            if not stack:
                del self.runs[room]
            each = room // length
            whole = min(have, n // each)
            offset = self.limit - room
            if whole:
                self._place(length, whole * each, first, each, offset)
                self._room(room - each * length, first, whole)
                n -= whole * each
            if whole < have:
                if 0 < n < each:
                    self._place(length, n, first + whole, n, offset)
                    self._room(room - n * length, first + whole, 1)
                    n, whole = 0, whole + 1
                self._room(room, first + whole, have - whole)


def best_plan(counts: dict[int, int], limit: int = LIMIT, schemes: tuple = SCHEMES) -> Plan:
    """The scheme's plan with the fewest sequences; none is tried after one that no packing betters."""
    least, best = -(-sum(n * c for n, c in counts.items()) // limit), None
    for small, groups in schemes:
        plan = Plan(counts, limit, small, groups)
        if best is None or plan.sequences < best.sequences:
            best = plan
        if best.sequences == least:
            break
    return best


def pieces(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", end_id: int = 2, limit: int = LIMIT, remembered: int = MOST_PIECES, batch_bytes: int = 2 << 20) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, row) of whole texts; row numbers the pieces, from the task up.

    remembered and batch_bytes trade a worker's memory for its speed.
    """
    schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("row", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enter("ids")
        row = TaskContext.get().partitionId() << 40
        enc, end = encoder(tokenizer, remembered), np.array([end_id], "<u4").tobytes()
        for batch in slices(batches, most=batch_bytes):
            flat, lengths = enc.encode_bytes(*laid(batch.column(1)))
            ids = memoryview(flat.astype("<u4", copy=False)).cast("B")
            names, numbers, starts, sizes, crcs = [], [], [], [], []
            e = 0
            for d, n in zip(batch.column(0).to_pylist(), lengths.tolist(), strict=True):
                s, e, total = e, e + n, n + 1
                a = 0
                for k, b in enumerate(range(total % limit or limit, total + 1, limit)):
                    crc = zlib.crc32(ids[4 * (s + a) : 4 * min(s + b, e)])
                    names.append(d)
                    numbers.append(k)
                    starts.append(a)
                    sizes.append(b - a)
                    crcs.append(zlib.crc32(end, crc) if b == total else crc)
                    a = b
            rows = np.arange(row, row + len(names))
            row += len(names)
            out = [names, numbers, starts, sizes, crcs, rows]
            yield record(schema, *out)

    return texts(docs).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, row long")


def pack(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", end_id: int = 2, limit: int = LIMIT, schemes: tuple = SCHEMES, **memory: int) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) of every piece."""
    spark = docs.sparkSession
    cut = materialise(pieces(docs, tokenizer, end_id, limit, **memory), "pieces")
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    cut = cut.withColumn("bucket", F.pmod(F.xxhash64("row"), F.lit(buckets)).cast("int"))
    sizes = materialise(cut.groupBy("length", "bucket").agg(F.count("*").alias("n")), "lengths")
    plan = best_plan({r[0]: r[1] for r in sizes.groupBy("length").agg(F.sum("n")).collect()}, limit, schemes)
    before = sizes.select("length", "bucket", F.coalesce(F.sum("n").over(W.partitionBy("length").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    kinds = T.StructType([T.StructField(n, T.LongType()) for n in ("p_length", "rank_from", "n", "sequence_from", "each", "base")])
    rows = spark.createDataFrame(plan.rows, kinds)
    ranked = cut.withColumn("_k", F.row_number().over(W.partitionBy("length", "bucket").orderBy("row")) - 1)
    ranked = ranked.join(before.hint("merge"), ["length", "bucket"]).withColumn("_rank", F.col("before") + F.col("_k"))
    placed = ranked.join(F.broadcast(rows), (F.col("length") == F.col("p_length")) & (F.col("_rank") >= F.col("rank_from")) & (F.col("_rank") < F.col("rank_from") + F.col("n")))
    inside = F.col("_rank") - F.col("rank_from")
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("sequence_from") + F.floor(inside / F.col("each"))).cast("long").alias("sequence_id"), (F.col("base") + (inside % F.col("each")) * F.col("length")).cast("long").alias("offset"))
