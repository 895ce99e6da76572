"""One pass over each stream with all candidates at once, as an Arrow kernel.

Candidates wait under the event types they can take next. A node remembers, for what has been reached, the latest start
of an occurrence ending there; entries out of reach are dropped as a probe or a new entry passes them. A completed episode counts
and forgets everything it remembered. The last node is updated first, so that an event takes one node of an episode.
"""

from __future__ import annotations

from collections import defaultdict, deque

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode

COUNTS = "stream string, ep_id string, freq long, peak_entries long"


class _Parallel:
    """Latest time of each type; on completion all are forgotten."""

    def __init__(self, e: Episode, expiry: int):
        self.types, self.expiry, self.seen, self.freq, self.peak = e.types, expiry, {}, 0, 0

    def dump(self) -> list:
        return [self.freq, self.seen]

    def load(self, state: list) -> None:
        self.freq, self.seen = state

    def take(self, x: str, t: int) -> None:
        seen = self.seen
        seen[x] = t
        self.peak = max(self.peak, len(seen))
        if len(seen) == len(self.types):
            old = t - self.expiry
            if min(seen.values()) >= old:
                self.freq += 1
                seen.clear()
            else:
                for k in [k for k, v in seen.items() if v < old]:
                    del seen[k]


class _Serial:
    """Each node holds (time, latest start) of what ends there; the next node looks for the latest start in its window."""

    def __init__(self, e: Episode, expiry: int | None):
        self.types, self.gaps, self.expiry = e.types, e.gaps, expiry
        self.at = [k for k in range(len(e.types))][::-1]
        self.held = [deque() for _ in e.types]
        self.freq = self.peak = 0

    def dump(self) -> list:
        return [self.freq, [list(d) for d in self.held]]

    def load(self, state: list) -> None:
        self.freq, self.held = state[0], [deque(map(tuple, d)) for d in state[1]]

    def take(self, x: str, t: int) -> None:
        last = len(self.types) - 1
        for k in self.at:
            if self.types[k] != x:
                continue
            if k == 0:
                start = t
            else:
                entries = self.held[k - 1]
                lo, hi = (self.gaps[k - 1].lo, self.gaps[k - 1].hi) if self.gaps else (0, None)
                while hi is not None and entries and t - entries[0][0] > hi:
                    entries.popleft()
                start = max((s for when, s in entries if t - when > lo), default=None)
            if start is None:
                continue
            if k == last:
                if self.expiry is None or t - start <= self.expiry:
                    self.freq += 1
                    for d in self.held:
                        d.clear()
                    return
            else:
                own = self.held[k]
                while self.gaps and own and t - own[0][0] > self.gaps[k].hi:
                    own.popleft()
                if not self.gaps:  # without gaps an earlier entry with an earlier start is of no more use, but for ties
                    while own and own[-1][1] <= start and own[-1][0] == t:
                        own.pop()
                    if len(own) > 1 and own[-1][0] < t:
                        own.popleft()
                own.append((t, start))
                self.peak = max(self.peak, sum(map(len, self.held)))


def machine(e: Episode, expiry: int | None) -> _Parallel | _Serial:
    """What counts one episode: take(type, time) in order, freq, and dump() and load() of what it remembers."""
    return _Parallel(e, expiry) if e.kind == "parallel" else _Serial(e, expiry)


def run(types: list[str], times: list[int], episodes: list[Episode], expiry: int | None = None) -> list[tuple[str, int, int]]:
    """(ep_id, freq, peak entries) over one stream in its order."""
    machines = [machine(e, expiry) for e in episodes]
    waits = defaultdict(list)
    for e, m in zip(episodes, machines, strict=True):
        for x in set(e.types):
            waits[x].append(m)
    for x, t in zip(types, times, strict=True):
        for m in waits.get(x, ()):
            m.take(x, t)
    return [(e.id, m.freq, m.peak) for e, m in zip(episodes, machines, strict=True)]


def count_by_stream(stream: DataFrame, episodes: list[Episode], expiry: int | None = None) -> DataFrame:
    """For many streams of a size that a task can hold; a stream that is longer goes to the windowed form."""
    schema = pa.schema([("stream", pa.string()), ("ep_id", pa.string()), ("freq", pa.int64()), ("peak_entries", pa.int64())])

    def kernel(key: tuple, table: pa.Table) -> pa.Table:
        table = table.sort_by([("t", "ascending"), ("eid", "ascending")])
        rows = [(key[0].as_py(), *r) for r in run(table["etype"].to_pylist(), table["t"].to_pylist(), episodes, expiry) if r[1] or r[2]]
        return pa.Table.from_arrays([pa.array([r[k] for r in rows], f.type) for k, f in enumerate(schema)], schema=schema)

    return stream.groupBy("stream").applyInArrow(kernel, COUNTS)


def count(stream: DataFrame, episodes: list[Episode], expiry: int | None = None) -> DataFrame:
    return count_by_stream(stream, episodes, expiry).groupBy("ep_id").agg(F.sum("freq").alias("freq")).where("freq > 0")


def run_order(types: list[str], times: list[int], nodes: list[str], edges: list[tuple[int, int]], expiry: int | None = None) -> int:
    """Disjoint occurrences of a general episode: nodes[a] strictly before nodes[b] for each edge, others in any order.

    For each set of matched nodes the latest start is kept; which of them were matched in the present tick is kept along,
    since an edge needs a later tick.
    """
    before = [sum(1 << a for a, b in edges if b == v) for v in range(len(nodes))]
    full, freq, held, i = (1 << len(nodes)) - 1, 0, {}, 0
    while i < len(times):
        now, t = {(d, 0): s for d, s in held.items()}, times[i]
        while i < len(times) and times[i] == t:
            snapshot = [((0, 0), t), *now.items()]
            for v, x in enumerate(nodes):
                if x != types[i]:
                    continue
                for (d, tick), start in snapshot:
                    if not d >> v & 1 and before[v] & d == before[v] and not before[v] & tick:
                        key = (d | 1 << v, tick | 1 << v)
                        now[key] = max(start, now.get(key, start))
            done = [s for (d, _), s in now.items() if d == full and (expiry is None or t - s <= expiry)]
            if done:
                freq, now = freq + 1, {}
            i += 1
        held = {}
        for (d, _), s in now.items():
            if d != full and (expiry is None or t - s <= expiry):
                held[d] = max(s, held.get(d, s))
    return freq


def count_order(stream: DataFrame, nodes: list[str], edges: list[tuple[int, int]], expiry: int | None = None) -> DataFrame:
    """(freq) of a general episode over all streams; the states grow with the width of its order, so it should be small."""
    if len(nodes) > 12:
        raise ValueError("an episode of more than 12 nodes has too many states")

    def kernel(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["t", "eid"])
        return pd.DataFrame({"freq": [run_order(pdf["etype"].tolist(), pdf["t"].tolist(), nodes, edges, expiry)]})

    return stream.groupBy("stream").applyInPandas(kernel, "freq long").agg(F.sum("freq").alias("freq"))


def naive_count(stream: DataFrame, episodes: list[Episode], latest: bool) -> DataFrame:
    """Gap episodes by an occurrence that is built without the intervals and tested afterwards: it misses valid ones.

    latest: each node takes the latest entry before it (innermost occurrence), else the first one (leftmost).
    """

    def one(types: list[str], times: list[int], e: Episode) -> int:
        chains: list[list[int] | None] = [None] * len(e.types)
        freq = 0
        for x, t in zip(types, times, strict=True):
            for k in range(len(e.types) - 1, -1, -1):
                if e.types[k] != x or (k and (chains[k - 1] is None or chains[k - 1][-1] >= t)):
                    continue
                if chains[k] is None or latest:
                    chains[k] = ([] if k == 0 else chains[k - 1]) + [t]
            full = chains[-1]
            if full is not None:
                if all(g.lo < b - a <= g.hi for a, b, g in zip(full, full[1:], e.gaps, strict=False)):
                    freq += 1
                chains = [None] * len(e.types)
        return freq

    def kernel(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["t", "eid"])
        x, t = pdf["etype"].tolist(), pdf["t"].tolist()
        return pd.DataFrame([(e.id, one(x, t, e)) for e in episodes], columns=["ep_id", "freq"])

    return stream.groupBy("stream").applyInPandas(kernel, "ep_id string, freq long").groupBy("ep_id").agg(F.sum("freq").alias("freq"))
