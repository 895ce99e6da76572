"""Levels over streams that a task can hold, counted where they lie.

Occurrences never cross streams, so that a task that holds whole streams needs nothing of another one: streams are laid
end to end with more than a span between them, as blocks of some 260,000 events, coded and written once to the shared
folder. A level is one pass over the blocks, and only candidates and their counts travel. Pairs are found all at once, from
the events next to each other; larger episodes with the arrays of `recording`. Counts are those of the distributed plans,
which take over where a stream is longer than `MOST` or holds two events of one position.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode, Gap
from ..storage import new_path
from .recording import Recording

MOST, BLOCK, NEIGHBOURS = 500_000, 1 << 18, 16
SCHEMA = "names array<string>, cuts binary, n long, code binary, t binary, tied boolean"
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def packed(stream: DataFrame) -> DataFrame:
    """(stream, etypes, ts, eids): a row for each stream, its events in order."""
    rows = stream.where("stream is not null").groupBy("stream").agg(F.array_sort(F.collect_list(F.struct("t", "eid", "etype"))).alias("x"))
    return rows.select("stream", F.col("x.etype").alias("etypes"), F.col("x.t").alias("ts"), F.col("x.eid").alias("eids"))


def longest(stream: DataFrame) -> int:
    return stream.groupBy("stream").count().agg(F.max("count")).first()[0] or 0


def _flat(column: pa.Array) -> np.ndarray:
    return pc.cast(column.flatten(), pa.int64()).to_numpy(zero_copy_only=False)


def _row(parts: list[tuple], span: int) -> list:
    """parts: (names, lengths, codes, ts, tied) of some streams; laid end to end."""
    lengths = np.concatenate([p[1] for p in parts])
    code, t = np.concatenate([p[2] for p in parts]).astype(np.int32), np.concatenate([p[3] for p in parts]).astype(np.int64)
    cuts = np.cumsum(lengths) - lengths
    if len(t):
        opens, ends = t[cuts], t[cuts + lengths - 1]
        room = ends - opens + span + 2
        t = t + np.repeat(np.cumsum(room) - room - opens, lengths)
    squeeze = lambda x: pa.compress(x.tobytes(), codec="zstd", asbytes=True)
    return [[x for p in parts for x in p[0]], cuts.astype(np.int64).tobytes(), len(t), squeeze(code), squeeze(np.diff(t, prepend=0)), any(p[4] for p in parts)]


def encode(rows: DataFrame, types: list[str], span: int) -> DataFrame:
    """Blocks of the packed streams, of events of these types alone. rows: (stream, etypes) and, where an event's tick isn't its place in the array, ts and eids."""
    spark, timed = rows.sparkSession, "ts" in rows.columns
    now = "".join(x for x in spark.conf.get(_BATCH) if x.isdigit())
    if not now or not 0 < int(now) <= 16 << 20:
        spark.conf.set(_BATCH, str(16 << 20))
    schema = pa.schema([("names", pa.list_(pa.string())), ("cuts", pa.binary()), ("n", pa.int64()), ("code", pa.binary()), ("t", pa.binary()), ("tied", pa.bool_())])

    def write(parts: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([x], type=f.type) for x, f in zip(_row(parts, span), schema, strict=True)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, parts, held = pa.array(types, pa.string()), [], 0
        for batch in batches:
            lists = batch.column(1)
            if not batch.num_rows:
                continue
            code = pc.fill_null(pc.index_in(lists.flatten(), value_set=known), -1).to_numpy(zero_copy_only=False)
            counts = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            first = np.cumsum(counts) - counts
            whose, keep = np.repeat(np.arange(len(counts)), counts), code >= 0
            t = _flat(batch.column(2)) if timed else np.arange(len(code)) - np.repeat(first, counts)
            tied = False
            if timed and len(t):
                eid = _flat(batch.column(3))
                tied = bool((keep[1:] & keep[:-1] & (whose[1:] == whose[:-1]) & (t[1:] == t[:-1]) & (eid[1:] == eid[:-1])).any())
            code, t = code[keep], t[keep]
            lengths = np.bincount(whose[keep], minlength=len(counts))
            own = np.flatnonzero(lengths)
            names, ends = batch.column(0).take(pa.array(own)).to_pylist(), np.cumsum(lengths[own])
            a = 0
            while a < len(own):  # as many whole streams as the block has room for, one at least
                base = ends[a - 1] if a else 0
                b = max(a + 1, int(np.searchsorted(ends, base + BLOCK - held, "right")))
                parts.append((names[a:b], lengths[own[a:b]], code[base : ends[b - 1]], t[base : ends[b - 1]], tied))
                held, a = held + int(ends[b - 1] - base), b
                if held >= BLOCK or a < len(own):
                    yield write(parts)
                    parts, held = [], 0
        if parts:
            yield write(parts)

    path = new_path(spark, "blocks")
    rows.select("stream", "etypes", *(["ts", "eids"] if timed else [])).mapInArrow(run, SCHEMA).write.parquet(path)
    return spark.read.schema(SCHEMA).parquet(path)


def tied(blocks: DataFrame) -> bool:
    return not blocks.where("tied").select("n").isEmpty()


class Block(Recording):
    """A block's events, already in order; types are their codes."""

    def __init__(self, code: np.ndarray, t: np.ndarray, m: int):
        self.code, self.t = code, t
        by_type = np.argsort(code, kind="stable")
        cuts = np.searchsorted(code[by_type], np.arange(m + 1))
        self.places = {i: by_type[cuts[i] : cuts[i + 1]] for i in range(m)}
        self.grown: dict = {}

    def interval(self, e: Episode, reach: int | None) -> tuple[np.ndarray, np.ndarray]:
        if e.kind == "parallel":
            return self.group(e.types, reach)
        if len(e.types) == 1:
            return (self.places[e.types[0]],) * 2
        p = e.prefix()
        if p not in self.grown:
            self.grown[p] = self.interval(p, reach)
        return self.further(self.grown[p], e.types[-1], e.gaps[-1])

    def pairs(self, m: int, lo: int, hi: int, ordered: bool) -> np.ndarray | None:
        """Counts of all pairs (first * m + second) whose distance is in (lo, hi], by the events just before each one;
        None where too many are within reach. Unordered pairs: of different types, the smaller code first."""
        n, at = len(self.t), np.arange(len(self.t))
        lags = int((at - np.searchsorted(self.t, self.t - hi, "left")).max(initial=0))
        if lags > NEIGHBOURS:
            return None
        keys, near = [], []
        for lag in range(1, lags + 1):
            a, b = self.code[:-lag].astype(np.int64), self.code[lag:].astype(np.int64)
            dt = self.t[lag:] - self.t[:-lag]
            fits = (dt > lo) & (dt <= hi)
            nearest = fits.copy()
            for k, (code, ok) in enumerate(near, 1):  # a nearer one of its type comes later
                nearest &= ~(ok[lag - k :] & (code[lag - k :] == a))
            near.append((a, fits))
            if not ordered:
                nearest &= a != b
                a, b = np.minimum(a, b), np.maximum(a, b)
            took = np.flatnonzero(nearest)
            keys.append((((a[took] * m + b[took]) * n + took + lag) * (NEIGHBOURS + 1)) + lag)
        out = np.zeros(m * m, np.int64)
        if not keys:
            return out
        key = np.sort(np.concatenate(keys))
        place, lag = key // (NEIGHBOURS + 1), key % (NEIGHBOURS + 1)
        pair = place // n
        heads = np.flatnonzero(np.append(True, pair[1:] != pair[:-1])) if len(pair) else np.empty(0, np.int64)
        stops = np.append(heads[1:], len(pair))
        after = np.searchsorted(place - lag, place, "right")  # the first that starts later; starts never fall
        name, now = pair[heads], heads
        while len(now):
            out[name] += 1
            now = after[now]
            on = now < stops
            name, now, stops = name[on], now[on], stops[on]
        return out


def _opened(batches: Iterator[pa.RecordBatch], m: int) -> Iterator[tuple[Block, np.ndarray, list[str]]]:
    for batch in batches:
        for i in range(batch.num_rows):
            n = batch.column(2)[i].as_py()
            opened = lambda k, kind: np.frombuffer(pa.decompress(batch.column(k)[i].as_buffer(), n * np.dtype(kind).itemsize, codec="zstd"), kind)  # noqa: B023, E731
            yield Block(opened(3, np.int32), np.cumsum(opened(4, np.int64)), m), np.frombuffer(batch.column(1)[i].as_py(), np.int64), batch.column(0)[i]


def _coded(e: Episode, code: dict[str, int]) -> Episode:
    return Episode(e.kind, tuple(code[x] for x in e.types), e.gaps)


def _summed(blocks: DataFrame, run, least: int) -> list[tuple[int, int]]:
    rows = blocks.mapInArrow(run, "i long, freq long").groupBy("i").agg(F.sum("freq").alias("freq")).where(F.col("freq") >= least)
    return [(r["i"], r["freq"]) for r in rows.collect()]


def _counts(total: np.ndarray) -> pa.RecordBatch:
    i = np.flatnonzero(total)
    return pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(total[i], pa.int64())], names=["i", "freq"])


def pairs(blocks: DataFrame, types: list[str], kind: str, reach: int | None, gaps: tuple[Gap, ...], least: int, allow_self: bool = True) -> list[tuple[Episode, int]]:
    """All frequent episodes of two types."""
    m, serial = len(types), kind == "serial"
    bounds = [(g.lo, g.hi) for g in gaps] if serial else [(-1, reach)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(bounds) * m * m, np.int64)
        for block, _, _ in _opened(batches, m):
            for g, (lo, hi) in enumerate(bounds):
                part, found = total[g * m * m : (g + 1) * m * m], block.pairs(m, lo, hi, serial)
                if found is not None:
                    part += found
                    continue
                for a in range(m):
                    for b in range(0 if serial else a + 1, m):
                        e = Episode(kind, (a, b), (gaps[g],) if serial else ())
                        part[a * m + b] += block.count(block.interval(e, reach), 1)
        yield _counts(total)

    out = []
    for i, f in _summed(blocks, run, least):
        g, a, b = i // (m * m), i // m % m, i % m
        if a != b or (serial and allow_self):
            pair = (types[a], types[b]) if serial else tuple(sorted((types[a], types[b])))
            out.append((Episode(kind, pair, (gaps[g],) if serial else ()), f))
    return out


def count(blocks: DataFrame, types: list[str], episodes: list[Episode], reach: int | None, least: int) -> list[tuple[Episode, int]]:
    """The frequent ones of the episodes, and how often they occur."""
    code = {x: i for i, x in enumerate(types)}
    listed, m = [_coded(e, code) for e in episodes], len(types)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(listed), np.int64)
        for block, _, _ in _opened(batches, m):
            for i, e in enumerate(listed):
                total[i] += block.count(block.interval(e, reach), 1)
        yield _counts(total)

    return [(episodes[i], f) for i, f in _summed(blocks, run, least)]
