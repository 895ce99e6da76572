"""Rates from data, surrogates, profiles of the highest frequency by size, p-values and thresholds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Gap, latest, parallel, pos, unpacked
from ..storage import cut
from . import candidates, frequency, occurrences


def mean_rates(stream: DataFrame, tick: int) -> DataFrame:
    """(etype, lam): how often a second each type occurs over the whole stream; tick: what stands for a millisecond."""
    each = stream.groupBy("etype").agg(F.count("*").alias("n"), F.min("t").alias("t0"), F.max("t").alias("t1"))
    whole = each.agg((F.max("t1") - F.min("t0")).alias("ticks"))
    return each.crossJoin(F.broadcast(whole)).where("ticks > 0").select("etype", (F.col("n") * 1000.0 * tick / F.col("ticks")).alias("lam"))


def estimate_rates(stream: DataFrame, window: int) -> DataFrame:
    """(stream, etype, w, n): events of a type in the tumbling window [w, w + 1) * window."""
    return stream.groupBy("stream", "etype", F.floor(F.col("t") / window).alias("w")).agg(F.count("*").alias("n"))


def _congruence(*terms: tuple) -> Column:
    """A number below 2^31 for each row, the same in any engine: terms (column, factor) through two linear congruences."""
    total = F.lit(12345).cast("long")
    for column, factor in terms:
        total = total + F.pmod(column.cast("long"), F.lit(1 << 31)) * factor
    return F.pmod(F.pmod(total, F.lit(1 << 31)) * 69069 + 1, F.lit(1 << 31))


def calibrated_null(stream: DataFrame, window: int, n_sets: int, seed: int) -> DataFrame:
    """Data sets with the data's count of each type in each window: every event at a time drawn anew within its window."""
    rows = stream.select("*", F.explode(F.sequence(F.lit(0), F.lit(n_sets - 1))).alias("d"))
    high, low = (_congruence((F.col("eid"), f), (F.col("d"), 2654435761), (F.lit(seed), 40503)) for f in (1103515245, 22695477))
    t = F.floor(F.col("t") / window) * window + F.pmod(high * (1 << 31) + low, F.lit(window))
    return rows.select(F.concat_ws("/", "stream", F.col("d").cast("string")).alias("stream"), "etype", t.cast("long").alias("t"), "eid")


def jitter(stream: DataFrame, width: int, n_sets: int, seed: int = 1) -> DataFrame:
    """Each event moved within (-width, width) by a linear congruence of its eid; one stream for each data set."""
    rows = stream.select("*", F.explode(F.sequence(F.lit(0), F.lit(n_sets - 1))).alias("d"))
    u = _congruence((F.col("eid"), 1103515245), (F.col("d"), 2654435761), (F.lit(seed), 40503))
    moved = F.col("t") + F.pmod(u, F.lit(2 * width - 1)) - (width - 1)
    return rows.select(F.concat_ws("/", "stream", F.col("d").cast("string")).alias("stream"), "etype", moved.cast("long").alias("t"), "eid")


def dataset(stream: F.Column) -> F.Column:
    return F.element_at(F.split(stream, "/"), -1)


#: Types near an event beyond which groups are listed level by level instead of from each event's own subsets.
CROWD = 14


def null_counts(null: DataFrame, kind: str, max_k: int, expiry: int | None = None, gaps: tuple[Gap, ...] = (), chunk: int | None = None, least: int = 1) -> DataFrame:
    """(dataset, k, ep_id, freq) of all episodes seen at least `least` times in a data set, of all data sets at once.

    Orders with least above 1 grow from what was found so often in their data set only, which any longer one needs.
    """
    single = null.groupBy("stream", F.col("etype").alias("ep_id")).agg(F.count("*").alias("freq")).withColumn("k", F.lit(1))
    if kind == "parallel":
        near = cut(occurrences.recents(null, expiry))
        crowd = near.agg(F.max(F.size("near"))).first()[0] or 0
        raw = _subsets(near, max_k) if crowd <= CROWD else _levels(near, max_k)
        named = raw.select("stream", F.concat_ws("|", F.col("k").cast("string"), "ep_id").alias("ep_id"), "s", "e")
        parts = F.split("ep_id", r"\|", 2)
        counted = frequency.count_by_stream(named, chunk).select("stream", parts[1].alias("ep_id"), "freq", parts[0].cast("int").alias("k"))
    else:
        counted, grown = None, None
        for k in range(2, max_k + 1):
            grown = occurrences.serial_pairs(null, *gaps) if k == 2 else _grow_all(grown, null, gaps)
            if k < max_k or k > 2:
                grown = cut(grown)
            found = frequency.count_by_stream(grown, chunk)
            if least > 1 and k < max_k:
                found = cut(found.where(F.col("freq") >= least))
                grown = grown.join(found.select("stream", "ep_id"), ["stream", "ep_id"], "left_semi")
            found = found.withColumn("k", F.lit(k))
            counted = found if counted is None else counted.unionByName(found)
    every = single if counted is None else single.unionByName(counted)
    sums = every.groupBy(dataset(F.col("stream")).alias("dataset"), "k", "ep_id").agg(F.sum("freq").alias("freq"))
    return sums.where(F.col("freq") >= least)


def _levels(near: DataFrame, max_k: int) -> DataFrame:
    """Intervals of every group of 2 to max_k types that is seen, each level's groups from those of the one before it."""
    raw = cut(occurrences.parallel_pairs(near)).withColumn("k", F.lit(2))
    level = raw
    for k in range(3, max_k + 1):
        seen = [parallel(r["ep_id"].split("+")) for r in level.select("ep_id").distinct().collect()]
        episodes = candidates.next_parallel(seen)
        if not episodes:
            break
        level = cut(occurrences.parallel_intervals(near, episodes)).withColumn("k", F.lit(k))
        raw = raw.unionByName(level)
    return raw


def _subsets(near: DataFrame, max_k: int) -> DataFrame:
    """Intervals of every group of 2 to max_k types that an event closes."""
    own = F.create_map("etype", F.struct("t", "eid"))
    others = F.map_filter("near", lambda k, v: k != F.col("etype"))
    names = F.array_sort(F.map_keys(others))
    sets = F.array(F.array().cast("array<string>"))
    grown = F.aggregate(names, sets, lambda a, x: F.concat(a, F.transform(F.filter(a, lambda y: F.size(y) < max_k - 1), lambda y: F.concat(y, F.array(x)))))
    rows = near.withColumn("all", F.map_concat(others, own)).select("stream", "t", "eid", "etype", "all", F.explode(F.filter(grown, lambda y: F.size(y) > 0)).alias("g"))
    types = F.array_sort(F.concat("g", F.array("etype")))
    return rows.select("stream", F.array_join(types, "+").alias("ep_id"), F.array_min(F.transform(types, lambda x: F.element_at(F.col("all"), x))).alias("s"), F.struct("t", "eid").alias("e"), F.size(types).alias("k"))


def _grow_all(grown: DataFrame, stream: DataFrame, gaps: tuple[Gap, ...]) -> DataFrame:
    """Every episode one event longer, by every gap: one join over the gaps' hull."""
    lo, hi = min(g.lo for g in gaps), max(g.hi for g in gaps)
    both = occurrences.band_join(grown.select("stream", "ep_id", "s", F.col("e.t").alias("t")), stream, lo, hi)
    dt, label = F.col("r.t") - F.col("l.t"), F.lit(None).cast("string")
    for g in gaps:
        label = F.when((dt > g.lo) & (dt <= g.hi), F.lit(g.label)).otherwise(label)
    rows = both.withColumn("_g", label).where("_g is not null")
    keys = [F.col("l.ep_id").alias("_p"), "_g", F.col("r.etype").alias("_x"), F.col("r.t").alias("t"), F.col("r.eid").alias("eid")]
    found = rows.groupBy("stream", "_b", *keys).agg(latest(F.col("l.s")).alias("s"))
    return found.select("stream", F.concat("_p", F.lit("-"), "_g", F.lit("->"), "_x").alias("ep_id"), unpacked(F.col("s")).alias("s"), pos().alias("e"))


def max_freq_profile(counts: DataFrame, max_k: int, n_sets: int) -> DataFrame:
    """By size: average, largest and smallest of the data sets' highest frequency (0 where a set has none)."""
    tops = counts.groupBy("dataset", "k").agg(F.max("freq").alias("top"))
    sizes = counts.sparkSession.range(1, max_k + 1).select(F.col("id").cast("int").alias("k"))
    sums = tops.groupBy("k").agg(F.sum("top").alias("s"), F.max("top").alias("hi"), F.min("top").alias("lo"), F.count("*").alias("n"))
    return sizes.join(sums, "k", "left").select("k", F.round(F.coalesce("s", F.lit(0)) / n_sets, 6).alias("avg_max"), F.coalesce("hi", F.lit(0)).cast("long").alias("max_max"), F.when(F.coalesce("n", F.lit(0)) == n_sets, F.col("lo")).otherwise(0).cast("long").alias("min_max"))


def min_freq_profile(counts: DataFrame) -> DataFrame:
    """counts: (dataset, k, ep_id, freq) of planted episodes. By size: average, largest, smallest of the lowest frequency."""
    low = counts.groupBy("dataset", "k").agg(F.min("freq").alias("low"))
    return low.groupBy("k").agg(F.round(F.avg("low"), 6).alias("avg_min"), F.max("low").alias("max_min"), F.min("low").alias("min_min"))


def p_values(frequent: DataFrame, null_tops: DataFrame, n_sets: int, add_one: bool = False) -> DataFrame:
    """frequent: (ep_id, k, freq); null_tops: (dataset, k, top). The share of data sets that reach the frequency."""
    tops = null_tops.groupBy("k").agg(F.array_sort(F.collect_list("top")).alias("tops"))  # one number for each data set
    hits = F.size(F.filter(F.coalesce("tops", F.array().cast("array<bigint>")), lambda x: x >= F.col("freq")))
    p = (hits + 1) / (n_sets + 1) if add_one else hits / n_sets
    return frequent.join(F.broadcast(tops), "k", "left").select("ep_id", "k", "freq", F.round(p, 6).alias("p"))


def threshold_for(null_tops: DataFrame, alpha: float) -> DataFrame:
    """By size: the smallest frequency above the (1 - alpha) quantile of the null's highest."""
    return null_tops.groupBy("k").agg((F.floor(F.percentile("top", 1 - alpha)) + 1).cast("long").alias("threshold"))
