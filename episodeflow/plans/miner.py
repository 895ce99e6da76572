"""The level-wise loop: count, retain, generate, until nothing is left.

Frequent episodes of a level are metadata and come to the driver; intervals stay distributed. Those of frequent episodes
alone are written to the checkpoint folder between levels, so that lineage doesn't grow and lost executors cost one level
at most. Streams are counted chunk by chunk of time.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode, Gap, gap_set
from ..operators import candidates as C
from ..operators import frequency as Q
from ..operators import occurrences as O
from ..storage import cut as _cut
from . import blocks as B
from . import recording

FREQUENT = "ep_id string, kind string, k int, types array<string>, gaps array<string>, freq long, rel_freq double, maximal boolean"
LEVELS = "k int, n_candidates long, n_frequent long, max_freq long, min_freq long, wall_ms long"


@dataclass(frozen=True)
class EpisodePlan:
    """What to mine. threshold: a count (int) or a share of the stream's length (float); zero means at least once."""

    kind: str
    threshold: float
    expiry: int | None = None
    gaps: tuple[Gap, ...] = ()
    max_k: int | None = None
    strict_threshold: bool = False
    strict_expiry: bool = False
    allow_self: bool = True
    prune: str = "auto"

    def __post_init__(self):
        if self.kind not in ("parallel", "serial"):
            raise ValueError(f"no such kind of episode: {self.kind}")
        if self.kind == "parallel" and self.expiry is None:
            raise ValueError("parallel episodes need an expiry")
        if self.gaps:
            object.__setattr__(self, "gaps", tuple(gap_set(list(self.gaps))))

    def least(self, length: int) -> int:
        at = self.threshold * length if isinstance(self.threshold, float) else self.threshold
        return max(1, int(at) + 1 if self.strict_threshold else -int(-at // 1))

    def sound_prune(self) -> str:
        """Any subset is as frequent without gaps; with them only what is left after dropping an end."""
        return self.prune if self.prune != "auto" else "ends" if self.gaps else "all"


@dataclass
class MiningResult:
    rows: list[tuple[Episode, int]]
    levels: list[tuple]
    length: int
    passes: int = 0
    chunk: int | None = None
    recorded: bool = False

    def largest(self) -> tuple[int, int]:
        """The largest size and how many episodes have it."""
        k = max((len(e.types) for e, _ in self.rows), default=0)
        return k, sum(len(e.types) == k for e, _ in self.rows)

    def maximal(self) -> set[str]:
        return maximal_ids([e for e, _ in self.rows])

    def frequent(self, spark) -> DataFrame:
        top = self.maximal()
        return spark.createDataFrame([(e.id, e.kind, len(e.types), list(e.types), [g.label for g in e.gaps], f, f / max(1, self.length), e.id in top) for e, f in self.rows], FREQUENT)

    def level_stats(self, spark) -> DataFrame:
        return spark.createDataFrame(self.levels, LEVELS)


def maximal_ids(episodes: list[Episode]) -> set[str]:
    """Episodes that aren't part of a frequent one that is larger by a node."""
    covered = set()
    for e in episodes:
        if e.kind == "parallel":
            covered |= {Episode("parallel", e.types[:i] + e.types[i + 1 :]).id for i in range(len(e.types))}
        elif len(e.types) > 1:
            covered |= {e.prefix().id, e.suffix().id}
    return {e.id for e in episodes} - covered


def _small(df: DataFrame, rows: int) -> DataFrame:
    """A table from the driver, broadcast where it has few rows."""
    return F.broadcast(df) if rows <= 200_000 else df


def _recorded(stream: DataFrame, plan: EpisodePlan, result: MiningResult, least: int) -> MiningResult:
    """The result from one job over a recording that a task can hold."""
    reach = plan.expiry if not plan.strict_expiry or plan.expiry is None else plan.expiry - 1
    rows = recording.levels(stream, plan.kind, reach, plan.gaps, least, plan.max_k, plan.sound_prune(), plan.allow_self).collect()
    for k in sorted({r["k"] for r in rows}):
        own = [r for r in rows if r["k"] == k]
        found = [(Episode(plan.kind, tuple(r["types"]), tuple(plan.gaps[g] for g in r["gaps"])), r["freq"]) for r in own if r["types"]]
        freqs = [f for _, f in found]
        result.rows += found
        result.levels.append((k, own[0]["n_candidates"], len(found), max(freqs, default=0), min(freqs, default=0), own[0]["wall_ms"]))
    result.passes, result.recorded = len(result.levels), True
    return result


def _streams(rows: DataFrame, plan: EpisodePlan, result: MiningResult, least: int, types: list[str]) -> MiningResult | None:
    """The result level by level over blocks of whole streams; none where events share a position."""
    reach = None if plan.expiry is None else plan.expiry - plan.strict_expiry
    blocks = B.encode(rows, types, reach if plan.kind == "parallel" else max(g.hi for g in plan.gaps))
    if B.tied(blocks):
        return None
    found, m, k = [e for e, _ in result.rows], len(types), 2
    while found and (plan.max_k is None or k <= plan.max_k):
        began = time.time()
        if k == 2:
            n = m * (m - 1) // 2 if plan.kind == "parallel" else m * (m if plan.allow_self else m - 1) * len(plan.gaps)
            counted = B.pairs(blocks, types, plan.kind, reach, plan.gaps, least, plan.allow_self) if n else []
        else:
            cands = C.next_parallel(found) if plan.kind == "parallel" else C.next_serial(found, plan.sound_prune())
            if not plan.allow_self:
                cands = [e for e in cands if len(set(e.types)) == len(e.types)]
            n = len(cands)
            counted = B.count(blocks, types, cands, reach, least) if n else []
        if not n:
            break
        result.passes += 1
        counted.sort(key=lambda x: x[0].id)
        _level(result, k, n, counted, began)
        found, k = [e for e, _ in counted], k + 1
    return result


def mine(stream: DataFrame, plan: EpisodePlan, strategy: str = "auto", packed: DataFrame | None = None) -> MiningResult:
    """All frequent episodes of the plan; frequency is summed over streams.

    strategy: windowed (a job a level, any size), recording (one job, one task: groups, and orders with gaps), streams
    (blocks of whole streams, for streams a task can hold; packed: the stream in the form of blocks.packed, where that is
    at hand), or auto, which takes the second for recordings of up to recording.MOST events. The counts are the same.
    """
    if strategy not in ("auto", "windowed", "recording", "streams"):
        raise ValueError(f"no such strategy: {strategy}")
    began = time.time()
    # The types that aren't frequent stay distributed: there may be millions.
    each = _cut(stream.groupBy("etype").agg(F.count("*").alias("count"), F.min("t").alias("t0"), F.max("t").alias("t1")))
    whole = each.agg(F.count("*").alias("types"), F.sum("count").alias("n"), F.min("t0").alias("t0"), F.max("t1").alias("t1")).first()
    length = whole["n"] or 0
    chunk = None  # one for all streams: a stream that holds most events is spread, short ones have one chunk each
    if length:
        span = plan.expiry if plan.expiry is not None else max((g.hi for g in plan.gaps), default=None)
        chunk = Q.chunk_of(whole["t1"] - whole["t0"], length, span)
    least = plan.least(length)
    result = MiningResult([], [], length, 1, chunk)
    bounded = plan.gaps or (plan.kind == "parallel" and plan.expiry >= plan.strict_expiry)
    if strategy == "recording" and not bounded:
        raise ValueError("orders without gaps aren't counted in one task")
    if strategy == "recording" or (strategy == "auto" and bounded and length <= recording.MOST):
        return _recorded(stream, plan, result, least)
    singles = each.where(F.col("count") >= least).select("etype", "count").collect()
    found = sorted(((Episode(plan.kind, (r["etype"],)), r["count"]) for r in singles), key=lambda x: x[0].types)
    _level(result, 1, whole["types"], found, began)
    spark = stream.sparkSession
    kept = {e.types[0] for e, _ in found}
    if strategy == "streams" and kept and bounded and (packed is not None or B.longest(stream) <= B.MOST):
        done = _streams(B.packed(stream) if packed is None else packed, plan, result, least, sorted(kept))
        if done:
            return done
    if kept and len(kept) < whole["types"]:
        stream = stream.join(_small(spark.createDataFrame([(x,) for x in sorted(kept)], "etype string"), len(kept)), "etype", "left_semi").select("stream", "etype", "t", "eid")
    near = intervals = None
    k = 2
    while found and (plan.max_k is None or k <= plan.max_k):
        began = time.time()
        frequent = [e for e, _ in found]
        m = len(frequent)
        if plan.kind == "parallel":
            # All pairs are counted at once; listing them would cost the square of the alphabet.
            cands = [] if k == 2 else C.next_parallel(frequent)
            n_cands = m * (m - 1) // 2 if k == 2 else len(cands)
            if not n_cands:
                break
            if near is None:
                near = _cut(O.same_tick(stream) if plan.expiry == 0 else O.recents(stream, plan.expiry, plan.strict_expiry))
            raw = O.parallel_pairs(near) if k == 2 else O.parallel_intervals(near, cands)
        elif plan.gaps:
            cands = [] if k == 2 else C.next_serial(frequent, plan.sound_prune())
            if not plan.allow_self:
                cands = [e for e in cands if len(set(e.types)) == len(e.types)]
            n_cands = m * (m if plan.allow_self else m - 1) * len(plan.gaps) if k == 2 else len(cands)
            if not n_cands:
                break
            # Pairs are counted as they come; only those found frequent are written for the next level.
            raw = O.serial_pairs(stream, *plan.gaps) if k == 2 else O.serial_extend(intervals, stream, cands)
            if k > 2:
                raw = intervals = _cut(raw)
        else:
            cands = [Episode("serial", (a.types[0], b.types[0])) for a in frequent for b in frequent if plan.allow_self or a != b] if k == 2 else C.next_serial(frequent, plan.sound_prune())
            n_cands = len(cands)
            if not cands:
                break
            raw = O.serial_span(stream, cands, plan.expiry)
        by_id = {e.id: e for e in cands}
        counted = Q.count(raw, chunk).where(F.col("freq") >= least).collect()
        result.passes += 1
        pairs = ((by_id.get(r["ep_id"]) or (_pair(r["ep_id"], plan, kept) if not cands else None), r["freq"]) for r in counted)
        found = sorted(((e, f) for e, f in pairs if e), key=lambda x: x[0].id)
        _level(result, k, n_cands, found, began)
        if plan.kind == "serial" and plan.gaps and found and (plan.max_k is None or k < plan.max_k):
            if k == 2:
                intervals = _cut(O.serial_extend(O.singles(stream), stream, [e for e, _ in found]))
            else:
                ids = [(e.id,) for e, _ in found]
                intervals = intervals.join(_small(spark.createDataFrame(ids, "ep_id string"), len(ids)), "ep_id", "left_semi").select("stream", "ep_id", "s", "e")
        k += 1
    return result


def _pair(ep_id: str, plan: EpisodePlan, types: set[str]) -> Episode | None:
    """The two-node episode of an id; its types are frequent ones, whatever characters they hold."""
    for gap in plan.gaps or (None,):
        mark, at = "+" if gap is None else f"-{gap.label}->", -1
        while (at := ep_id.find(mark, at + 1)) >= 0:
            a, b = ep_id[:at], ep_id[at + len(mark) :]
            if a in types and b in types and (a != b or (gap is not None and plan.allow_self)):
                return Episode(plan.kind, (a, b), (gap,) if gap else ())
    return None


def _level(result: MiningResult, k: int, n: int, found: list, began: float) -> None:
    if found or k == 1:
        result.rows += found
    freqs = [f for _, f in found]
    result.levels.append((k, n, len(found), max(freqs, default=0), min(freqs, default=0), int(1000 * (time.time() - began))))


def best_intervals(frequent: DataFrame) -> DataFrame:
    """For each tuple of types the gaps with the highest frequency (ties: the smaller id)."""
    from pyspark.sql import Window as W

    order = W.partitionBy("types").orderBy(F.desc("freq"), "ep_id")
    return frequent.withColumn("_r", F.row_number().over(order)).where("_r = 1").drop("_r")
