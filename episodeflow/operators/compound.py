"""Occurrences with their members, groups rewritten to compound events, and chains of groups."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode
from ..plans import miner, recording
from . import frequency, occurrences


def track(stream: DataFrame, episodes: list[Episode], expiry: int | None = None, chunk: int | None = None) -> DataFrame:
    """The counted occurrences: (stream, ep_id, s, e, members, occ_no); chunk: ticks, for long streams."""
    if episodes and episodes[0].kind == "parallel":
        near = occurrences.same_tick(stream) if expiry == 0 else occurrences.recents(stream, expiry)
        raw = occurrences.parallel_intervals(near, episodes, members=True)
    else:
        raw = occurrences.serial_intervals(stream, episodes, members=True)
    return frequency.select_disjoint(raw, chunk)


def raster(occurrences_: DataFrame, t0: int, t1: int) -> DataFrame:
    """Members of the occurrences within [t0, t1), as points to draw."""
    inside = occurrences_.where((F.col("s.t") >= t0) & (F.col("e.t") < t1))
    return inside.select("stream", "ep_id", "occ_no", F.explode("members").alias("m")).select("stream", "ep_id", "occ_no", F.col("m.etype").alias("etype"), F.col("m.t").alias("t"), F.col("m.eid").alias("eid"))


def compound_name(ep_id) -> F.Column:
    return F.concat(F.lit("["), F.translate(ep_id, "+", " "), F.lit("]"))


def rewrite(stream: DataFrame, occs: DataFrame, anchor: str = "midpoint", mode: str = "replace") -> DataFrame:
    """Each occurrence becomes one event at the middle of its span (or the mean of its members); its eid is their least.

    mode: replace takes the members out (claimed by any occurrence), augment leaves them in, types takes all events of the
    members' types out, whether they are claimed or not, so that a group's types are found in its compound alone.
    """
    if anchor not in ("midpoint", "mean") or mode not in ("replace", "augment", "types"):
        raise ValueError(f"no such anchor or mode: {anchor}, {mode}")
    middle = F.floor((F.col("s.t") + F.col("e.t")) / 2)
    mean = F.floor(F.aggregate("members", F.lit(0).cast("bigint"), lambda a, m: a + m["t"]) / F.size("members"))
    new = occs.select("stream", compound_name(F.col("ep_id")).alias("etype"), (middle if anchor == "midpoint" else mean).cast("long").alias("t"), F.array_min(F.transform("members", lambda m: m["eid"])).alias("eid"))
    if mode == "replace":
        claimed = occs.select("stream", F.explode("members.eid").alias("eid")).distinct()
        stream = stream.join(claimed, ["stream", "eid"], "left_anti").select("stream", "etype", "t", "eid")
    elif mode == "types":
        members = occs.select(F.explode("members.etype").alias("etype")).distinct()
        stream = stream.join(members, "etype", "left_anti").select("stream", "etype", "t", "eid")
    return stream.unionByName(new)


def mine_chain(stream: DataFrame, groups: miner.EpisodePlan, chain: miner.EpisodePlan, anchor: str = "midpoint", mode: str = "replace", strategy: str = "auto") -> tuple[miner.MiningResult, DataFrame, miner.MiningResult]:
    """Groups, the stream with maximal groups rewritten, and serial episodes over it."""
    found = miner.mine(stream, groups, strategy)
    top = found.maximal()
    episodes = [e for e, _ in found.rows if e.id in top and len(e.types) > 1]
    if episodes:
        if found.recorded and not groups.strict_expiry:
            stream = miner._cut(recording.rewritten(stream, episodes, groups.expiry, anchor, mode))
        else:
            reach = groups.expiry - groups.strict_expiry
            stream = miner._cut(rewrite(stream, track(stream, episodes, reach, found.chunk), anchor, mode))
    return found, stream, miner.mine(stream, replace(chain, kind="serial"), strategy)
