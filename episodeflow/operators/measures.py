"""Measures over frequent episodes: maximality, recovery, confidence, trend, structure, similarity of episode sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def maximal(frequent: DataFrame) -> DataFrame:
    """frequent: (ep_id, types, ...) of parallel episodes. Those that aren't a node short of another frequent one."""
    size = F.size("types")
    drops = frequent.where(size > 1).select(F.explode(F.transform(F.sequence(F.lit(0), size - 1), lambda i: F.filter("types", lambda x, j: j != i))).alias("types")).distinct()
    return frequent.join(drops, "types", "left_anti")


def _members(node: Column) -> Column:
    """The types of a node; a compound's stand in brackets."""
    return F.when(node.startswith("[") & node.endswith("]"), F.split(F.substring(node, F.lit(2), F.length(node) - 2), " ")).otherwise(F.array(node))


def _fits(node: Column, planted: Column, kind: str) -> Column:
    return node == planted if kind != "chain" else F.size(F.array_except(_members(node), _members(planted))) == 0


def embedded(types: Column, planted: Column, kind: str) -> Column:
    """Whether an episode is part of a planted one. parallel: a subset; serial: in the same order, others may stand between;
    chain: the same, and a group may lack some of the planted group's types."""
    if kind == "parallel":
        return F.size(F.array_except(types, planted)) == 0

    def step(at: Column, x: Column) -> Column:
        later = F.filter(F.sequence(F.lit(0), F.size(planted) - 1), lambda i: (i >= at) & _fits(x, F.get(planted, i), kind))
        return F.when((at >= 0) & (F.size(later) > 0), F.get(later, F.lit(0)) + 1).otherwise(F.lit(-1))

    return F.aggregate(types, F.lit(0), step) > 0


def recovery(frequent: DataFrame, truth: DataFrame, kind: str = "parallel") -> DataFrame:
    """frequent: (types, freq); truth: (planted array). By size: share inside a planted pattern, and the least frequency there.

    kind: parallel, serial or chain (nodes named like compound events). An episode meets the patterns that hold its first
    type only.
    """
    if kind not in ("parallel", "serial", "chain"):
        raise ValueError(f"no such kind of episode: {kind}")
    member = (lambda node: F.explode(_members(node))) if kind == "chain" else None
    planted = truth.select("planted", F.explode("planted").alias("_first"))
    if member:
        planted = planted.select("planted", member(F.col("_first")).alias("_first"))
    first = F.get(_members(F.get("types", F.lit(0))), F.lit(0)) if kind == "chain" else F.get("types", F.lit(0))
    inside = frequent.withColumn("_first", first).join(planted.distinct(), "_first").where(embedded(F.col("types"), F.col("planted"), kind)).select("types", F.lit(1).alias("_in"))
    rows = frequent.join(inside.distinct(), "types", "left")
    return rows.groupBy(F.size("types").alias("k")).agg(F.round(100 * F.count("_in") / F.count("*"), 6).alias("pct_embedded"), F.min(F.when(F.col("_in").isNotNull(), F.col("freq"))).alias("min_count"))


def average_runs(runs: list[DataFrame]) -> DataFrame:
    """Means over data sets of what `recovery` gives for each."""
    every = runs[0]
    for r in runs[1:]:
        every = every.unionByName(r)
    return every.groupBy("k").agg(F.round(F.avg("pct_embedded"), 2).alias("pct_embedded"), F.round(F.avg("min_count"), 1).alias("min_count"))


def pair_confidence(pairs: DataFrame, singles: DataFrame, on: tuple[str, ...] = ()) -> DataFrame:
    """pairs: (*on, a, b, freq); singles: (*on, etype, n). freq(a then b) / freq(a)."""
    one = singles.select(*on, F.col("etype").alias("a"), F.col("n").alias("n_a"))
    return pairs.join(one, [*on, "a"]).select(*on, "a", "b", "freq", F.round(F.col("freq") / F.col("n_a"), 6).alias("conf"))


def frequency_trend(by_day: DataFrame) -> DataFrame:
    """by_day: (day, ep_id, freq, n). The slope of freq / n over days, and the last day's step."""
    rel = by_day.withColumn("rel_freq", F.col("freq") / F.col("n"))
    last = W.partitionBy("ep_id").orderBy("day")
    rel = rel.withColumn("step", F.col("rel_freq") - F.lag("rel_freq").over(last))
    return rel.groupBy("ep_id").agg(F.count("*").alias("days"), F.round(F.regr_slope("rel_freq", "day"), 9).alias("slope"), F.round(F.max_by("step", "day"), 9).alias("last_step"))


def connectivity(serial_pairs: DataFrame) -> DataFrame:
    """serial_pairs: (types, gaps, freq) of any size: distinct consecutive edges with their gap and best frequency."""
    i = F.explode(F.sequence(F.lit(0), F.size("types") - 2)).alias("i")
    each = serial_pairs.where(F.size("types") > 1).select("types", "gaps", "freq", i)
    return each.select(F.get("types", F.col("i")).alias("src"), F.get("types", F.col("i") + 1).alias("dst"), F.get("gaps", F.col("i")).alias("gap"), "freq").groupBy("src", "dst", "gap").agg(F.max("freq").alias("freq"))


def peel_similarity(sets: DataFrame, n: int, pairs: DataFrame | None = None, multiset: bool = False) -> DataFrame:
    """sets: (slice, types) of episodes of size n. Sum over sizes i of 2^i times the episodes in common.

    Common episodes count and leave; the others lose their first or their last node (both ways) and are compared again,
    down to a single node. Episodes are sets: what arises twice counts once; as a multiset it counts and leaves as often
    as both sides have it. pairs: (a, b) of slices, else all.
    """
    slices = sets.select("slice").distinct()
    if pairs is None:
        pairs = slices.select(F.col("slice").alias("a")).crossJoin(F.broadcast(slices.select(F.col("slice").alias("b"))))
    left = pairs.join(sets.select(F.col("slice").alias("a"), "types"), "a").select("a", "b", "types")
    right = pairs.join(sets.select(F.col("slice").alias("b"), "types"), "b").select("a", "b", "types")
    if not multiset:
        left, right = left.distinct(), right.distinct()
    total = pairs.select("a", "b", F.lit(0).cast("bigint").alias("v"))
    keys = ["a", "b", "types"]
    for i in range(n, 0, -1):
        common = left.intersectAll(right) if multiset else left.join(right, keys, "left_semi")
        total = total.unionByName(common.groupBy("a", "b").agg((F.count("*") * (1 << i)).alias("v")))
        if i == 1:
            break
        halves = F.explode(F.array(F.slice("types", 1, i - 1), F.slice("types", 2, i - 1))).alias("types")
        if multiset:
            left, right = (side.exceptAll(common).select("a", "b", halves) for side in (left, right))
        else:
            left, right = (side.join(common, keys, "left_anti").select("a", "b", halves).distinct() for side in (left, right))
    return total.groupBy("a", "b").agg(F.sum("v").alias("sim"))


def peel_lists(lists: DataFrame, n: int, pairs: DataFrame | None = None) -> DataFrame:
    """What `peel_similarity` gives for sets of episodes, for short ones that a row can hold: a row a pair, no join of episodes.

    lists: (slice, sets array<array<string>>) of episodes of size n; pairs: (a, b), else all. A side without a list has none.
    """
    left, right = (lists.select(F.col("slice").alias(x), F.array_distinct("sets").alias(f"_{x}")) for x in "ab")
    if pairs is None:
        rows = left.crossJoin(F.broadcast(right))
    else:
        rows = pairs.join(left, "a", "left").join(right, "b", "left")
    none, total = F.array().cast("array<array<string>>"), F.lit(0).cast("bigint")
    rows = rows.select("a", "b", *[F.coalesce(f"_{x}", none).alias(f"_{x}") for x in "ab"], total.alias("sim"))
    for i in range(n, 0, -1):
        rows = rows.withColumn("_c", F.array_intersect("_a", "_b")).withColumn("sim", F.col("sim") + F.size("_c").cast("bigint") * (1 << i))
        if i > 1:
            halves = lambda e: F.array(F.slice(e, 1, i - 1), F.slice(e, 2, i - 1))  # noqa: B023, E731
            rows = rows.withColumns({x: F.array_distinct(F.flatten(F.transform(F.array_except(x, "_c"), halves))) for x in ("_a", "_b")})
    return rows.select("a", "b", "sim")


def top_by_slice(counts: DataFrame, q: int) -> DataFrame:
    """counts: (slice, ep_id, freq, ...). The q most frequent of each slice; ties: the smaller ep_id."""
    order = W.partitionBy("slice").orderBy(F.desc("freq"), "ep_id")
    return counts.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= q)
