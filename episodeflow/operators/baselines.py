"""What mining is compared with: correlograms, listed patterns, exhaustive enumeration, window counts, analytic nulls."""

from __future__ import annotations

from itertools import combinations, product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode, Gap, parallel, serial
from . import frequency, occurrences


def cross_correlogram(stream: DataFrame, max_lag: int, bin_: int) -> DataFrame:
    """(x, y, lag, n): pairs of events of x and y with y later by (lag * bin, (lag + 1) * bin], up to max_lag."""
    both = occurrences.band_join(stream, stream, 0, max_lag)
    lag = F.floor((F.col("r.t") - F.col("l.t") - 1) / bin_)
    return both.groupBy(F.col("l.etype").alias("x"), F.col("r.etype").alias("y"), lag.alias("lag")).agg(F.count("*").alias("n"))


def lagged_correlation(stream: DataFrame, bin_: int, lag: int, x: str, y: str) -> DataFrame:
    """Correlation of the binned counts of x and of y `lag` bins later, over the bins between the stream's ends."""
    binned = stream.select(F.floor(F.col("t") / bin_).alias("b"), "etype")
    ends = binned.agg(F.min("b").alias("b0"), F.max("b").alias("b1"))
    grid = ends.select(F.explode(F.sequence("b0", F.col("b1") - lag)).alias("b"))
    one = binned.where(F.col("etype") == x).groupBy("b").agg(F.count("*").alias("nx"))
    two = binned.where(F.col("etype") == y).groupBy((F.col("b") - lag).alias("b")).agg(F.count("*").alias("ny"))
    rows = grid.join(one, "b", "left").join(two, "b", "left").na.fill(0)
    return rows.agg(F.round(F.corr("nx", "ny"), 6).alias("r"), F.count("*").alias("bins"))


def lagged_correlations(stream: DataFrame, bin_: int, lags: list[int], types: list[str]) -> DataFrame:
    """(x, y, lag, r): the same of every two of `types` (named by the user) at every lag, from sums over bins that hold events.

    Bins without events add to no sum; the number of bins is known from the stream's ends.
    """
    spark = stream.sparkSession
    ends = stream.select(F.floor(F.col("t") / bin_).alias("b")).agg(F.min("b").alias("b0"), F.max("b").alias("b1"))
    counts = stream.where(F.col("etype").isin(types)).groupBy(F.floor(F.col("t") / bin_).alias("b"), "etype").agg(F.count("*").alias("n"))
    shift = F.broadcast(spark.createDataFrame([(k,) for k in lags], "lag long"))
    later = counts.crossJoin(shift).select(F.col("etype").alias("y"), (F.col("b") - F.col("lag")).alias("b"), "lag", F.col("n").alias("ny"))
    both = counts.select("b", F.col("etype").alias("x"), F.col("n").alias("nx")).join(later, "b").groupBy("x", "y", "lag").agg(F.sum(F.col("nx") * F.col("ny")).alias("xy"))
    # Of x the bins up to the last one but lag, of y those from the first one plus lag.
    sums = counts.crossJoin(shift).crossJoin(F.broadcast(ends))
    one, two = F.col("b") <= F.col("b1") - F.col("lag"), F.col("b") >= F.col("b0") + F.col("lag")
    total = lambda cond, name: [F.sum(F.when(cond, F.col("n"))).alias(name), F.sum(F.when(cond, F.col("n") * F.col("n"))).alias(f"{name}2")]
    per = sums.groupBy("etype", "lag", "b0", "b1").agg(*total(one, "sx"), *total(two, "sy"))
    x = per.select("lag", (F.col("b1") - F.col("b0") + 1 - F.col("lag")).alias("m"), F.col("etype").alias("x"), "sx", "sx2")
    rows = x.join(per.select("lag", F.col("etype").alias("y"), "sy", "sy2"), "lag").join(both, ["x", "y", "lag"], "left").na.fill(0)
    r = (F.col("m") * F.col("xy") - F.col("sx") * F.col("sy")) / F.sqrt((F.col("m") * F.col("sx2") - F.col("sx") ** 2) * (F.col("m") * F.col("sy2") - F.col("sy") ** 2))
    return rows.select("x", "y", "lag", F.round(r, 6).alias("r"))


def enumerate_all(stream: DataFrame, kind: str, k: int, expiry: int | None = None, gap: Gap | None = None, most: int = 20_000) -> DataFrame:
    """Frequencies of all combinations of k types, without candidate control; refuses more than `most` of them."""
    types = sorted(r["etype"] for r in stream.select("etype").distinct().collect())
    if len(types) ** k > most * (1 if kind == "serial" else 10):
        raise ValueError(f"{len(types)}^{k} candidates are more than {most}")
    if kind == "parallel":
        eps = [parallel(c) for c in combinations(types, k)]
        return frequency.count(occurrences.parallel_intervals(occurrences.recents(stream, expiry), eps))
    eps = [serial(c, (gap,) * (k - 1)) for c in product(types, repeat=k)]
    return frequency.count(occurrences.serial_intervals(stream, eps))


def expected_pairs(stream: DataFrame, expiry: int) -> DataFrame:
    """Independent Poisson channels: expected events of b within the expiry after one of a, n_a * rate_b * expiry."""
    ends = stream.agg((F.max("t") - F.min("t")).alias("length"))
    n = stream.groupBy("etype").agg(F.count("*").alias("n"))
    a, b = n.toDF("a", "n_a"), n.toDF("b", "n_b")
    return a.crossJoin(F.broadcast(b)).where("a < b").crossJoin(F.broadcast(ends)).select("a", "b", F.round(F.col("n_a") * F.col("n_b") * expiry / F.col("length"), 6).alias("expected"))


def brute_force_frequency(types: list[str], times: list[int], episode: Episode, expiry: int | None = None) -> int:
    """The maximum over all sets of disjoint occurrences, by trying every occurrence; for tests."""
    n = len(types)
    spans: set[tuple[int, int]] = set()

    def grow(k: int, chosen: tuple[int, ...]) -> None:
        if k == len(episode.types):
            lo, hi = min(chosen), max(chosen)
            if expiry is None or times[hi] - times[lo] <= expiry:
                spans.add((lo, hi))
            return
        for i in range(n):
            if types[i] != episode.types[k]:
                continue
            if episode.kind == "serial" and chosen:
                d = times[i] - times[chosen[-1]]
                ok = episode.gaps[k - 1].lo < d <= episode.gaps[k - 1].hi if episode.gaps else d > 0
                if not ok:
                    continue
            grow(k + 1, (*chosen, i))

    grow(0, ())
    count, end = 0, -1
    for lo, hi in sorted(spans, key=lambda x: x[1]):
        if lo > end:
            count, end = count + 1, hi
    return count
