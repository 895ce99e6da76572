"""Which way of counting a plan gets; all ways give the same numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode
from ..operators import automata, frequency, occurrences


def choose(n_streams: int, n_candidates: int, size: int, expiry: int | None, few_streams: int = 64, small: int = 512) -> str:
    """`ticks` for an expiry of zero, `kernel` for many streams and few candidates, else `windowed`."""
    if expiry == 0:
        return "ticks"
    return "kernel" if n_streams > few_streams and n_candidates * size <= small else "windowed"


def count(stream: DataFrame, episodes: list[Episode], expiry: int | None = None, strategy: str = "windowed", chunk: int | None = None) -> DataFrame:
    """(ep_id, freq) of listed episodes of one kind; a list given by the user is counted without any pruning.

    strategy: auto looks at the stream first; chunk: ticks, for long streams (auto finds it).
    """
    if strategy == "auto":
        seen = stream.agg(F.count("*").alias("n"), F.approx_count_distinct("stream").alias("streams"), F.min("t").alias("t0"), F.max("t").alias("t1")).first()
        strategy = choose(seen["streams"], len(episodes), max((len(e.types) for e in episodes), default=0), expiry)
        if seen["n"]:
            spans = [sum(g.hi for g in e.gaps) for e in episodes if e.gaps]
            chunk = frequency.chunk_of(seen["t1"] - seen["t0"], seen["n"], expiry if expiry is not None else max(spans, default=None))
    if strategy == "kernel":
        return automata.count(stream, episodes, expiry)
    if episodes and episodes[0].kind == "parallel":
        near = occurrences.same_tick(stream) if strategy == "ticks" or expiry == 0 else occurrences.recents(stream, expiry)
        return frequency.count(occurrences.parallel_intervals(near, episodes), chunk)
    if episodes and episodes[0].gaps:
        return frequency.count(occurrences.serial_intervals(stream, episodes), chunk)
    return frequency.count(occurrences.serial_span(stream, episodes, expiry), chunk)
