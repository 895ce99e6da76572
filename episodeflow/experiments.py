"""The published experiment workloads on simulated recordings: `python -m episodeflow.experiments NAME [datasets] [seconds]`.

Each experiment yields rows (dicts) with the numbers that are reported for it. Rates, delays, sizes, thresholds and intervals
the seconds of a recording are arguments; the defaults are smaller than the published 100 to 200 sets.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import Gap
from .operators import compound, frequency, measures, significance, simulator
from .plans import recording as one_job
from .plans.miner import EpisodePlan, MiningResult, _cut, best_intervals, mine
from .sources import streams as T

MS = 1000  # ticks
SYNC, STEP = MS, Gap(4 * MS, 6 * MS, "(4,6]")


def ms(lo: float, hi: float) -> Gap:
    return Gap(int(lo * MS), int(hi * MS), f"({lo:g},{hi:g}]")


def named(stream: DataFrame, letters: str) -> DataFrame:
    """Unit k under the k-th letter, the others under their number."""
    pairs = F.create_map(*[x for k, c in enumerate(letters) for x in (F.lit(str(k)), F.lit(c))])
    return stream.withColumn("etype", F.coalesce(F.element_at(pairs, F.col("etype")), "etype"))


def summary(label: str, found: MiningResult, seconds: float, show: int = 4) -> dict:
    k, n = found.largest()
    top = sorted(((f, e.id) for e, f in found.rows if len(e.types) == k), reverse=True)[:show] if k > 1 else []
    return {"run": label, "seconds": round(seconds, 2), "largest": k, "of_that_size": n, "best": [f"{i} {f}" for f, i in top]}


def timed(label: str, stream: DataFrame, plan: EpisodePlan) -> tuple[dict, MiningResult]:
    began = time.time()
    found = mine(stream, plan)
    return summary(label, found, time.time() - began), found


def network(n: int, layers: list[list[list[int]]], delays: list[int] | None = None, c: float = 0.5, seed: int = 1) -> simulator.Network:
    net = simulator.Network(n, simulator.random_network(n, 2, c, seed))
    for pattern in layers:
        simulator.plant(net, pattern, delays)
    return net


def recording(spark: SparkSession, net: simulator.Network, seconds: float, n: int = 1, seed: int = 1) -> DataFrame:
    return _cut(simulator.simulate(spark, net, seconds, n, seed))


def example1(spark: SparkSession, n: int = 1, seconds: float = 50) -> Iterator[dict]:
    """A, then B, then C and E together, then D and F together: expiries, then intervals."""
    s = named(recording(spark, network(26, [[[0], [1], [2, 4], [3, 5]]]), seconds), "ABCDEF")
    for expiry in (0.1, 1, 2, 7):
        yield timed(f"parallel, expiry {expiry} ms", s, EpisodePlan("parallel", 0.01, expiry=int(expiry * MS)))[0]
    for lo, hi in ((0, 1), (0, 2), (2, 4), (4, 6)):
        yield timed(f"serial, gap {lo}-{hi} ms", s, EpisodePlan("serial", 0.01, gaps=(ms(lo, hi),)))[0]


def example2(spark: SparkSession, n: int = 1, seconds: float = 50) -> Iterator[dict]:
    """A chain of groups: A, BCD, E, FGHI, J, KL."""
    s = named(recording(spark, network(26, [[[0], [1, 2, 3], [4], [5, 6, 7, 8], [9], [10, 11]]]), seconds), "ABCDEFGHIJKL")
    yield timed("parallel, expiry 1 ms", s, EpisodePlan("parallel", 0.01, expiry=SYNC))[0]
    for lo, hi in ((2, 4), (4, 6), (6, 8)):
        yield timed(f"serial, gap {lo}-{hi} ms", s, EpisodePlan("serial", 0.01, gaps=(ms(lo, hi),)))[0]
    for lo, hi in ((2, 4), (4, 6), (6, 8)):
        began = time.time()
        _, _, chains = compound.mine_chain(s, EpisodePlan("parallel", 0.01, expiry=SYNC), EpisodePlan("serial", 0.01, gaps=(ms(lo, hi),)), mode="types")
        yield summary(f"chain, gap {lo}-{hi} ms", chains, time.time() - began)


def example3(spark: SparkSession, n: int = 1, seconds: float = 50) -> Iterator[dict]:
    """Unequal delays: X, ABC, D, E, F; expiries, fixed intervals, and intervals discovered."""
    s = named(recording(spark, network(26, [[[0], [1, 2, 3], [4], [5], [6]]], [5, 3, 7, 3]), seconds), "XABCDEF")
    for expiry in (1, 2, 4, 6):
        yield timed(f"parallel, expiry {expiry} ms", s, EpisodePlan("parallel", 0.01, expiry=expiry * MS))[0]
    for lo, hi in ((0, 2), (2, 4), (4, 6), (6, 8)):
        yield timed(f"serial, gap {lo}-{hi} ms", s, EpisodePlan("serial", 0.01, gaps=(ms(lo, hi),)))[0]
    began = time.time()
    _, _, chains = compound.mine_chain(s, EpisodePlan("parallel", 0.01, expiry=SYNC), EpisodePlan("serial", 0.01, gaps=tuple(ms(lo, lo + 2) for lo in range(0, 10, 2))), mode="types")
    yield summary("chain, intervals discovered", chains, time.time() - began)
    best = best_intervals(chains.frequent(spark).where("k = 2"))
    yield {"run": "best intervals", "edges": [r["ep_id"] for r in best.orderBy(F.desc("freq")).limit(6).collect()]}


def _averages(spark: SparkSession, runs: list[DataFrame], sizes: tuple[int, ...]) -> list[tuple]:
    rows = measures.average_runs(runs).where(F.col("k").isin(*sizes)).orderBy("k").collect()
    return [tuple(r) for r in rows]


def _planted(spark: SparkSession, kind: str, size: int, patterns: int, n: int, seconds: float) -> dict:
    """A group that a unit of its own fires counts with that unit's followers only; an order with all its units."""
    if kind == "parallel":
        layers = [[[size * patterns + p], list(range(p * size, (p + 1) * size))] for p in range(patterns)]
        plan = EpisodePlan("parallel", 300, expiry=SYNC)
    else:
        layers = [[[i] for i in range(p * size, (p + 1) * size)] for p in range(patterns)]
        plan = EpisodePlan("serial", 300, gaps=(STEP,))
    runs, took = [], []
    every = recording(spark, network(64, layers), seconds, n)
    for k in range(n):
        s = every.where(F.col("stream") == str(k))
        row, found = timed(f"{kind} {size} x {patterns}", s, plan)
        took.append(row["seconds"])
        members = [[str(x) for layer in pattern[-1 if kind == "parallel" else 0 :] for x in layer] for pattern in layers]
        truth = spark.createDataFrame([(m,) for m in members], "planted array<string>")
        runs.append(_cut(measures.recovery(found.frequent(spark).select("types", "freq"), truth, kind)))
    return {"run": f"{kind}, size {size}, {patterns} patterns", "sets": n, "seconds": round(sum(took) / n, 2), "largest": row["largest"], "by_size": _averages(spark, runs, (1, 2, size))}


def planted_synchrony(spark: SparkSession, n: int = 5, seconds: float = 50) -> Iterator[dict]:
    for size in (8, 10, 12):
        for patterns in (2, 3, 4):
            yield _planted(spark, "parallel", size, patterns, n, seconds)


def planted_order(spark: SparkSession, n: int = 5, seconds: float = 50) -> Iterator[dict]:
    for size in (8, 10, 12):
        for patterns in (2, 3, 4):
            yield _planted(spark, "serial", size, patterns, n, seconds)


def planted_chains(spark: SparkSession, n: int = 3, seconds: float = 50) -> Iterator[dict]:
    """Groups of 5 and of 4 behind single units, groups in a row by patterns: groups first, then chains over the rewritten stream.

    All events of the groups' types leave the stream with the rewriting: that gives the published shares at size 1.
    Three chains of four groups of 5 need 72 units, so that recording has 72 instead of 64.
    """
    for group, shapes in ((5, ((4, 1), (4, 2), (4, 3), (6, 1))), (4, ((4, 1), (4, 2), (4, 3), (6, 1), (6, 2), (8, 1)))):
        for groups, patterns in shapes:
            size = groups * (group + 1)
            layers = [[x for g in range(groups) for x in ([p * size + g * (group + 1)], list(range(p * size + g * (group + 1) + 1, p * size + (g + 1) * (group + 1))))] for p in range(patterns)]
            found_runs, chain_runs, took = [], [], [0.0, 0.0]
            every = recording(spark, network(max(64, size * patterns), layers), seconds, n)
            for k in range(n):
                s = every.where(F.col("stream") == str(k))
                began = time.time()
                found = mine(s, EpisodePlan("parallel", 300, expiry=SYNC))
                middle = time.time()
                top = [e for e, _ in found.rows if e.id in found.maximal() and len(e.types) > 1]
                new = _cut(one_job.rewritten(s, top, SYNC, mode="types"))
                chains = mine(new, EpisodePlan("serial", 50, gaps=(STEP,), max_k=2 * groups))
                took[0] += middle - began
                took[1] += time.time() - middle
                one = spark.createDataFrame([([str(x) for x in layer],) for pattern in layers for layer in pattern if len(layer) > 1], "planted array<string>")
                line = spark.createDataFrame([(["[" + " ".join(sorted(map(str, layer))) + "]" if len(layer) > 1 else str(layer[0]) for layer in pattern],) for pattern in layers], "planted array<string>")
                found_runs.append(_cut(measures.recovery(found.frequent(spark).select("types", "freq"), one)))
                chain_runs.append(_cut(measures.recovery(chains.frequent(spark).select("types", "freq"), line, "chain")))
            label = f"groups of {group}, {groups} in a row, {patterns} patterns"
            yield {"run": f"{label}: groups", "sets": n, "seconds": round(took[0] / n, 2), "by_size": _averages(spark, found_runs, (1, 2, group))}
            yield {"run": f"{label}: chains", "sets": n, "seconds": round(took[1] / n, 2), "by_size": _averages(spark, chain_runs, (1, 2, 2 * groups))}


def _null(spark: SparkSession, n: int, seconds: float, model: str) -> DataFrame:
    return _cut(simulator.null_networks(spark, 26, 0.5, seconds, n, 3) if model == "network" else simulator.null_stream(spark, model, 26, seconds, n, 3))


def null_profiles(spark: SparkSession, n: int = 10, seconds: float = 50) -> Iterator[dict]:
    """Highest frequencies without any pattern, by size to 10: groups, order with one interval, order with three.

    Episodes seen once in a data set don't count (the published profiles hold none).
    """
    chunk = frequency.chunk_of(int(seconds * 1000 * MS), 26 * 20 * int(seconds), 6 * 9 * MS)
    for model in ("network", "fixed", "shared", "drift", "tied"):
        null = _null(spark, n, seconds, model)
        for label, kind, gaps, most in (("parallel", "parallel", (), 10), ("serial", "serial", (STEP,), 10), ("intervals discovered", "serial", (ms(2, 4), ms(4, 6), ms(6, 8)), 10)):
            if len(gaps) > 1 and model == "network":
                continue
            began = time.time()
            counts = significance.null_counts(null, kind, most, expiry=SYNC, gaps=gaps, chunk=chunk, least=2)
            rows = significance.max_freq_profile(counts, most, n).orderBy("k").collect()
            yield {"run": f"{model}, {label}", "sets": n, "seconds": round(time.time() - began, 1), "avg_max_min": [tuple(r)[1:] for r in rows]}


def planted_profiles(spark: SparkSession, n: int = 20, seconds: float = 50) -> Iterator[dict]:
    """Lowest frequency of a planted pattern of 10 by size, over data sets: of all parts that a group has, of an order's parts."""
    for kind in ("parallel", "serial"):
        layers = [[[10], list(range(10))]] if kind == "parallel" else [[[i] for i in range(10)]]
        every = recording(spark, network(26, layers), seconds, n)
        plan = EpisodePlan("parallel", 250, expiry=SYNC) if kind == "parallel" else EpisodePlan("serial", 250, gaps=(STEP,))
        truth = spark.createDataFrame([([str(i) for i in range(10)],)], "planted array<string>")
        runs = None
        for k in range(n):
            found = mine(every.where(F.col("stream") == str(k)), plan).frequent(spark).select("types", "freq")
            part = measures.recovery(found, truth, kind).select(F.lit(str(k)).alias("dataset"), "k", F.lit("").alias("ep_id"), F.col("min_count").alias("freq"))
            runs = part if runs is None else runs.unionByName(part)
        rows = significance.min_freq_profile(runs.where("freq is not null")).orderBy("k").collect()
        yield {"run": kind, "sets": n, "avg_max_min": [tuple(r) for r in rows]}


def p_bound(spark: SparkSession, n: int = 40, seconds: float = 50) -> Iterator[dict]:
    """How many of n null data sets, from all five models, reach a count of 300 with more than two nodes; thresholds from them."""
    tops = None
    models = ("network", "fixed", "shared", "drift", "tied")
    for model in models:
        counts = significance.null_counts(_null(spark, n // len(models), seconds, model), "parallel", 4, expiry=SYNC)
        part = counts.groupBy(F.concat(F.lit(f"{model}/"), "dataset").alias("dataset"), "k").agg(F.max("freq").alias("top"))
        tops = part if tops is None else tops.unionByName(part)
    tops, n = _cut(tops), n // len(models) * len(models)
    found = spark.createDataFrame([("any", 3, 300)], "ep_id string, k int, freq long")
    yield {"run": "p of 300 at size 3", "sets": n, "p": significance.p_values(found, tops, n).first()["p"], "below": 1 / n, "thresholds": [tuple(r) for r in significance.threshold_for(tops, 0.005).orderBy("k").collect()]}


def cultures(spark: SparkSession, n: int = 3, seconds: float = 30) -> Iterator[dict]:
    """Recordings of a few networks with orders of seven units, two slices each: similarity within and across networks.

    Published: 29 slices of ten minutes; here 2n slices of `seconds`.
    """
    parts = []
    for k in range(n):
        net = network(59, [[[(7 * k + i) % 59] for i in range(7)]], seed=k + 1)
        s = recording(spark, net, seconds, 2, k + 1)
        parts.append(s.withColumn("stream", F.concat(F.lit(f"{k}-"), "stream")))
    s = T.merge_streams(*parts)
    rows = []
    for name in [r[0] for r in s.select("stream").distinct().collect()]:
        found = mine(s.where(F.col("stream") == name), EpisodePlan("serial", int(2 * seconds), gaps=(Gap(0, 6 * MS),), max_k=7))
        best = sorted(((f, e) for e, f in found.rows if len(e.types) == 7), key=lambda x: (-x[0], x[1].id))[:20]
        rows += [(name, list(e.types)) for _, e in best]
    sets = spark.createDataFrame(rows, "slice string, types array<string>")
    for r in measures.peel_similarity(sets, 7).orderBy("a", "b").collect():
        yield {"a": r["a"], "b": r["b"], "sim": r["sim"]}


EXPERIMENTS = {f.__name__: f for f in (example1, example2, example3, planted_synchrony, planted_order, planted_chains, null_profiles, planted_profiles, p_bound, cultures)}


def main(args: list[str]) -> None:
    if not args or args[0] not in EXPERIMENTS:
        sys.exit(f"{__doc__}\n{', '.join(EXPERIMENTS)}")
    spark = SparkSession.builder.config("spark.ui.showConsoleProgress", "false").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    options = [int(args[1])] if len(args) > 1 else []
    if len(args) > 2:
        options.append(float(args[2]))
    for row in EXPERIMENTS[args[0]](spark, *options):
        print(json.dumps(row), flush=True)
    spark.stop()


if __name__ == "__main__":
    main(sys.argv[1:])
