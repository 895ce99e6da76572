"""Counts of all orders of k types at once, by stream, where no stream is longer than the largest gap.

There an order is an automaton whose state is the number of its nodes found so far. What a chunk of time does to an order,
from each of the k states, depends on the chunk's own events alone: chunks are counted wherever their task is, and a table
a chunk is looked up in order of time. No task holds a stream, and events are joined with none. Nodes need rising ticks and
occurrences rising positions, as everywhere: events of one tick lie in one chunk, and events of one position are no matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Gap, serial

BLOCK, LANES = 1 << 18, 1 << 18


def _starts(*columns: np.ndarray) -> np.ndarray:
    """Where a row differs from the one before it."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for x in columns:
        new[1:] |= x[1:] != x[:-1]
    return np.flatnonzero(new)


def _next(starts: np.ndarray, n: int) -> np.ndarray:
    """For each row where the group after its own begins."""
    ends = np.append(starts[1:], n)
    return np.repeat(ends, ends - starts)


def tables(code: np.ndarray, t: np.ndarray, eid: np.ndarray, opens: np.ndarray, m: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Events in order, in chunks that begin at opens; codes below 0 are of no type. For each chunk, order (its codes as
    digits to base m) and state before: the state after it, and how many occurrences end in it."""
    n, size, orders = len(code), m**k * k, np.array(list(product(range(m), repeat=k)), np.int64).reshape(-1, k)
    ends, chunk = np.append(opens[1:], n), np.repeat(np.arange(len(opens)), np.diff(np.append(opens, n)))
    later_tick, later_place = _next(_starts(chunk, t), n), _next(_starts(chunk, t, eid), n)
    at = np.arange(n)
    nearest = np.full((m, n + 1), n, np.int64)
    for i in range(m):
        nearest[i, :n] = np.minimum.accumulate(np.where(code == i, at, n)[::-1])[::-1]
    nearest = nearest.ravel()
    state, count = np.zeros(len(opens) * size, np.int8), np.zeros(len(opens) * size, np.int32)
    for a in range(0, len(state), LANES):
        lane = np.arange(a, min(a + LANES, len(state)))
        own, order, now = lane // size, lane % size // k, lane % k
        place, stop, row = opens[own], ends[own], order * k
        while len(lane):
            i = nearest[orders.ravel()[row + now] * (n + 1) + place]
            found = i < stop
            state[lane[~found]] = now[~found]
            lane, now, i, stop, row = lane[found], now[found] + 1, i[found], stop[found], row[found]
            done = now == k
            count[lane[done]] += 1
            place = np.where(done, later_place[i], later_tick[i])
            now[done] = 0
    return state.reshape(len(opens), -1), count.reshape(len(opens), -1)


def count_by_stream(stream: DataFrame, types: list[str], k: int, gap: Gap, chunk: int) -> DataFrame:
    """(stream, ep_id, freq) of every order of k of the types that occurs; gap: (0, hi], no stream being longer than hi; chunk in ticks."""
    m = len(types)

    def chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, parts, held, room = pa.array(types, pa.string()), [], 0, BLOCK

        def counted(rows: pa.Table, opens: np.ndarray) -> pa.RecordBatch:
            code = pc.fill_null(pc.index_in(rows.column("etype"), value_set=known), -1).to_numpy()
            eid = pc.fill_null(rows.column("eid"), np.iinfo(np.int64).min).to_numpy()
            state, count = tables(code, rows.column("t").to_numpy(), eid, opens, m, k)
            own = rows.select(["stream", "_c"]).take(pa.array(opens))
            blobs = [pa.array([x.tobytes() for x in side], pa.binary()) for side in (state, count)]
            return pa.RecordBatch.from_arrays([own.column("stream").combine_chunks(), own.column("_c").combine_chunks(), *blobs], names=["stream", "_c", "state", "n"])

        def borders(rows: pa.Table) -> np.ndarray:
            name = rows.column("stream").combine_chunks().dictionary_encode().indices.to_numpy()
            return _starts(name, rows.column("_c").to_numpy())

        for batch in batches:
            parts.append(batch)
            held += batch.num_rows
            if held < room:
                continue
            rows = pa.Table.from_batches(parts)
            opens = borders(rows)
            last = int(opens[-1])
            if last:
                yield counted(rows.slice(0, last), opens[:-1])
            parts, held = rows.slice(last).to_batches(), held - last
            room = max(BLOCK, 2 * held)  # a chunk is looked at whole
        if held:
            rows = pa.Table.from_batches(parts)
            yield counted(rows, borders(rows))

    def follow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = np.arange(m**k) * k
        ids = np.array([serial(x, (gap,) * (k - 1)).id for x in product(types, repeat=k)], object)

        def row(name: str | None, total: np.ndarray) -> pa.RecordBatch:
            i = np.flatnonzero(total)
            return pa.RecordBatch.from_arrays([pa.array([name] * len(i), pa.string()), pa.array(ids[i], pa.string()), pa.array(total[i])], names=["stream", "ep_id", "freq"])

        now, state, total = None, None, None
        for batch in batches:
            for i, name in enumerate(batch.column(0).to_pylist()):
                if name != now:
                    if now is not None:
                        yield row(now, total)
                    now, state, total = name, np.zeros(m**k, np.int64), np.zeros(m**k, np.int64)
                after, n = (np.frombuffer(batch.column(j)[i].as_py(), kind) for j, kind in ((2, np.int8), (3, np.int32)))
                total += n[each + state]
                state = after[each + state].astype(np.int64)
        if now is not None:
            yield row(now, total)

    rows = stream.where("stream is not null").select("stream", F.floor(F.col("t") / chunk).cast("long").alias("_c"), "etype", "t", "eid")
    met = rows.repartition("stream", "_c").sortWithinPartitions("stream", "_c", "t", "eid").mapInArrow(chunks, "stream string, _c long, state binary, n binary")
    return met.repartition("stream").sortWithinPartitions("stream", "_c").mapInArrow(follow, "stream string, ep_id string, freq long")
