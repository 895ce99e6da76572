"""Minimal intervals: for each event that can end an episode, the latest start from which it can be reached.

All joins in time are equi-joins on a bucket about as wide as the constraint, plus the exact test; a stream is thus
spread over tasks however long it is, and each event goes to two buckets at most.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..model import Episode, Gap, latest, pos, unpacked


def band_join(left: DataFrame, right: DataFrame, lo, hi, on: tuple[str, ...] = ("stream",), width: int | None = None) -> DataFrame:
    """Pairs (l, r) of rows with equal `on` and lo < r.t - l.t <= hi; both sides have t, the columns come as structs.

    lo and hi are numbers, or names of columns of left; then `width` says how wide a bucket is (the widest interval).
    _b is r's bucket. Aggregates by r that keep `on` and _b among their keys need no further shuffle.
    """
    if width is None:
        width = max(1, hi - max(lo, -1), hi // 2)
    lower, upper = (F.col(x) if isinstance(x, str) else F.lit(x) for x in (lo, hi))
    first, last = F.floor((F.col("t") + lower + 1) / width), F.floor((F.col("t") + upper) / width)
    a = left.select(*on, F.struct("*").alias("l"), F.explode(F.sequence(first.cast("long"), last.cast("long"))).alias("_b"))
    b = right.select(*on, F.struct("*").alias("r"), F.floor(F.col("t") / width).cast("long").alias("_b"))
    dt = F.col("r.t") - F.col("l.t")
    lower, upper = (F.col(f"l.{x}") if isinstance(x, str) else F.lit(x) for x in (lo, hi))
    return a.join(b, [*on, "_b"]).where((dt > lower) & (dt <= upper))


def recents(stream: DataFrame, expiry: int, strict: bool = False) -> DataFrame:
    """For each event, the latest position of every type within the expiry before it, itself included: map `near`."""
    reach = expiry - 1 if strict else expiry
    if reach < 0:
        raise ValueError("the expiry leaves no room for an event itself")
    both = band_join(stream, stream, -1, reach).where((F.col("l.t") < F.col("r.t")) | (F.col("l.eid") <= F.col("r.eid")))
    last = both.groupBy("stream", "_b", F.col("r.etype").alias("etype"), F.col("r.t").alias("t"), F.col("r.eid").alias("eid"), F.col("l.etype").alias("near_type")).agg(latest(pos("l")).alias("p")).withColumn("p", unpacked(F.col("p")))
    return last.groupBy("stream", "_b", "etype", "t", "eid").agg(F.map_from_entries(F.collect_list(F.struct("near_type", "p"))).alias("near")).drop("_b")


def same_tick(stream: DataFrame) -> DataFrame:
    """What `recents` gives for an expiry of 0, from one aggregation of each tick."""
    ticks = stream.groupBy("stream", "t").agg(F.array_sort(F.collect_list(F.struct("eid", "etype"))).alias("all"))
    each = ticks.select("stream", "t", "all", F.posexplode("all").alias("i", "e"))
    before = F.slice("all", F.lit(1), F.col("i") + 1)
    last = F.aggregate(before, F.create_map().cast("map<string,struct<t:bigint,eid:bigint>>"), lambda m, x: F.map_concat(F.map_filter(m, lambda k, v: k != x["etype"]), F.create_map(x["etype"], F.struct(F.col("t").alias("t"), x["eid"].alias("eid")))))
    return each.select("stream", F.col("e.etype").alias("etype"), "t", F.col("e.eid").alias("eid"), last.alias("near"))


def parallel_pairs(near: DataFrame) -> DataFrame:
    """Intervals of all two-type episodes at once, without candidates."""
    other = near.select("stream", "etype", "t", "eid", F.explode("near").alias("a", "s")).where("a <> etype")
    return other.select("stream", F.concat_ws("+", F.least("a", "etype"), F.greatest("a", "etype")).alias("ep_id"), "s", pos().alias("e"))


def parallel_intervals(near: DataFrame, episodes: list[Episode], members: bool = False) -> DataFrame:
    """Intervals of the episodes. A candidate waits under its closing type and its first other type."""
    spark = near.sparkSession
    rows = [(e.id, list(e.types), c, ([x for x in e.types if x != c] or [c])[0]) for e in episodes for c in e.types]
    waits = spark.createDataFrame(rows, "ep_id string, types array<string>, etype string, near_type string")
    keyed = near.select("stream", "etype", "t", "eid", "near", F.explode(F.map_keys("near")).alias("near_type"))
    met = keyed.join(F.broadcast(waits) if len(rows) <= 200_000 else waits, ["etype", "near_type"])
    met = met.where(F.forall("types", lambda x: F.map_contains_key("near", x)))
    places = F.transform("types", lambda x: F.element_at("near", x))
    extra = [F.transform("types", lambda x: F.struct(x.alias("etype"), F.element_at(F.col("near"), x)["t"].alias("t"), F.element_at(F.col("near"), x)["eid"].alias("eid"))).alias("members")] if members else []
    return met.select("stream", "ep_id", F.array_min(places).alias("s"), pos().alias("e"), *extra)


def serial_pairs(stream: DataFrame, *gaps: Gap) -> DataFrame:
    """Intervals of all two-type serial episodes with these (disjoint) gaps at once.

    One join over the hull of the gaps, then the gap that a distance falls in; where the hull is mostly holes, a join each.
    """
    lo, hi = min(g.lo for g in gaps), max(g.hi for g in gaps)
    if hi - lo > 4 * sum(g.hi - g.lo for g in gaps):
        out = serial_pairs(stream, gaps[0])
        for g in gaps[1:]:
            out = out.unionByName(serial_pairs(stream, g))
        return out
    both = band_join(stream, stream, lo, hi)
    dt, label = F.col("r.t") - F.col("l.t"), F.lit(None).cast("string")
    for g in gaps:
        label = F.when((dt > g.lo) & (dt <= g.hi), F.lit(g.label)).otherwise(label)
    rows = both.withColumn("_g", label).where("_g is not null")
    found = rows.groupBy("stream", "_b", F.col("l.etype").alias("a"), F.col("r.etype").alias("b"), "_g", F.col("r.t").alias("t"), F.col("r.eid").alias("eid")).agg(latest(pos("l")).alias("s"))
    return found.select("stream", F.concat("a", F.lit("-"), "_g", F.lit("->"), "b").alias("ep_id"), unpacked(F.col("s")).alias("s"), pos().alias("e"))


def serial_extend(intervals: DataFrame, stream: DataFrame, episodes: list[Episode], members: bool = False) -> DataFrame:
    """Raw intervals of the episodes from those of their prefixes: one for each end event, with the latest start.

    intervals: (stream, ep_id, s, e) of the prefixes, not thinned, since a dominated prefix may be the one that goes on.
    members: they also carry the members of the occurrence with that start. One join, whatever gaps the episodes end with.
    """
    rows = [(e.prefix().id, e.id, e.types[-1], e.gaps[-1].lo, e.gaps[-1].hi) for e in episodes]
    step = stream.sparkSession.createDataFrame(rows, "ep_id string, new_id string, etype string, lo long, hi long")
    left = intervals.join(F.broadcast(step) if len(rows) <= 200_000 else step, "ep_id").withColumn("t", F.col("e.t"))
    both = band_join(left, stream, "lo", "hi", ("stream", "etype"), max(e.gaps[-1].hi - e.gaps[-1].lo for e in episodes))
    keys = [F.col("stream"), F.col("etype").alias("_x"), F.col("_b"), F.col("l.new_id").alias("ep_id"), pos("r").alias("e")]
    if not members:
        found = both.groupBy("stream", "etype", "_b", F.col("l.new_id").alias("ep_id"), F.col("r.t").alias("t"), F.col("r.eid").alias("eid")).agg(latest(F.col("l.s")).alias("s"))
        return found.select("stream", "ep_id", unpacked(F.col("s")).alias("s"), pos().alias("e"))
    best = both.groupBy(*keys).agg(F.max(F.struct(F.col("l.s").alias("s"), F.col("l.e").alias("pe"), F.col("l.members").alias("m"))).alias("b"))
    return best.select("stream", "ep_id", F.col("b.s").alias("s"), "e", F.concat("b.m", F.array(F.struct(F.col("_x").alias("etype"), F.col("e.t").alias("t"), F.col("e.eid").alias("eid")))).alias("members"))


def singles(stream: DataFrame, members: bool = False) -> DataFrame:
    """Each event as the interval of its one-node episode."""
    extra = [F.array(F.struct("etype", "t", "eid")).alias("members")] if members else []
    return stream.select("stream", F.col("etype").alias("ep_id"), pos().alias("s"), pos().alias("e"), *extra)


def serial_intervals(stream: DataFrame, episodes: list[Episode], members: bool = False) -> DataFrame:
    """Raw intervals of listed gap episodes, grown node by node from their prefixes."""
    if not episodes:
        return singles(stream, members).where("false")
    out, size = None, max(len(e.types) for e in episodes)
    grown = singles(stream, members)
    wanted = {e.id for e in episodes}
    for k in range(1, size + 1):
        now = {p.id: p for e in episodes if len(e.types) >= k for p in [Episode("serial", e.types[:k], e.gaps[: k - 1])]}
        if k > 1:
            grown = serial_extend(grown, stream, list(now.values()), members)
        hits = [i for i in now if i in wanted]
        if hits:
            part = grown.where(F.col("ep_id").isin(hits))
            out = part if out is None else out.unionByName(part)
    return out


def serial_span(stream: DataFrame, episodes: list[Episode], expiry: int | None = None) -> DataFrame:
    """Raw intervals of serial episodes without gaps: the latest start chained over all earlier ticks, then the span test."""
    spark = stream.sparkSession
    out = None
    for size in sorted({len(e.types) for e in episodes}):
        rows = [(e.id, list(e.types)) for e in episodes if len(e.types) == size]
        eps = spark.createDataFrame(rows, "ep_id string, types array<string>")
        waits = eps.select("ep_id", "types", F.explode(F.array_distinct("types")).alias("etype"))
        df = stream.join(F.broadcast(waits) if len(rows) <= 200_000 else waits, "etype")
        w = W.partitionBy("stream", "ep_id").orderBy("t").rangeBetween(W.unboundedPreceding, -1)
        df = df.withColumn("_s0", F.when(F.col("etype") == F.col("types")[0], pos()))
        for k in range(1, size):
            df = df.withColumn(f"_s{k}", F.when(F.col("etype") == F.col("types")[k], F.max(f"_s{k - 1}").over(w)))
        part = df.where(F.col(f"_s{size - 1}").isNotNull()).select("stream", "ep_id", F.col(f"_s{size - 1}").alias("s"), pos().alias("e"))
        out = part if out is None else out.unionByName(part)
    return out if expiry is None else out.where(F.col("e.t") - F.col("s.t") <= expiry)


def span(interval: Column) -> Column:
    return interval["e"]["t"] - interval["s"]["t"]
