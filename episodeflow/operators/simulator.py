"""Spike trains from networks with planted patterns, and null streams.

A network is an edge list (src, dst, weight, delay in steps). Units fire as Poisson processes whose rate, constant
within a step, is a sigmoid of the weights of the spikes that arrive in it. A data set is sequential in time, so data
sets are the axis of parallelism; the rate-only nulls have no such dependence and are plain DataFrame expressions.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions import rates as R
from ..model import STREAM

TICKS = 1_000_000  # a second


@dataclass
class Network:
    """edges: (src, dst, weight, delay); own: unit -> rate of its own where it isn't lam_normal."""

    n: int
    edges: list[tuple[int, int, float, int]] = field(default_factory=list)
    own: dict[int, float] = field(default_factory=dict)
    truth: list[tuple] = field(default_factory=list)
    lam_normal: float = 20.0
    e_strong: float = 0.95
    dt: float = 0.001
    beta: float = 0.9
    alpha: float = 1.5
    refractory: float = 0.001

    @property
    def lam_max(self) -> float:
        return R.saturation(self.e_strong, self.dt)

    def strong(self, j: int) -> float:
        """The weight that lifts unit j, whatever its own rate, to beta of the highest rate."""
        return R.strong_weight(R.displacement(self.lam_max, self.own.get(j, self.lam_normal)), self.beta)


def random_network(n: int, scheme: int, c: float, seed: int, delay: int = 5) -> list[tuple[int, int, float, int]]:
    """Weights U[-c, c]. 1: random fan-out and that many receivers; 2: each ordered pair by a coin; 3: all pairs."""
    rng = np.random.default_rng(seed)
    out = []
    for i in range(n):
        others = [j for j in range(n) if j != i]
        if scheme == 1:
            others = rng.permutation(others)[: rng.integers(0, n)].tolist()
        elif scheme == 2:
            others = [j for j in others if rng.random() < 0.5]
        elif scheme != 3:
            raise ValueError(f"no such scheme: {scheme}")
        out += [(i, j, float(rng.uniform(-c, c)), delay) for j in others]
    return out


def plant(net: Network, layers: list[list[int]], delays: list[int] | None = None) -> Network:
    """Strong edges from each layer to the next; several senders share the weight, so that they must fire together.

    One unit a layer: an order; two layers of 1 and n: a synchrony; alternating: a chain of groups. All units but the
    first layer's get the compensated rate.
    """
    for layer in layers[1:]:
        for j in layer:
            net.own[j] = R.compensated(net.lam_normal, net.e_strong, net.alpha)
    for k, (a, b) in enumerate(zip(layers, layers[1:], strict=False)):
        net.edges += [(i, j, net.strong(j) / len(a), (delays or [5] * (len(layers) - 1))[k]) for i in a for j in b]
    net.truth.append(tuple(tuple(x) for x in layers))
    return net


def _fire(net: Network, seconds: float, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng, again = np.random.default_rng(seed), np.random.default_rng((seed, 1))
    steps = round(seconds / net.dt)
    reach = max((d for *_, d in net.edges), default=0) + 1
    weight = np.zeros((reach, net.n, net.n))
    for i, j, w, d in net.edges:
        weight[d, i, j] += w
    used = [d for d in range(reach) if weight[d].any()]
    lam_max = net.lam_max
    shift = np.array([R.displacement(lam_max, net.own.get(j, net.lam_normal)) for j in range(net.n)])
    arriving = np.zeros((reach, net.n))
    free = np.zeros(net.n)
    units, times = [], []
    uniform = rng.random((0, net.n))
    for k in range(steps):
        if k % 4096 == 0:
            uniform = -np.log1p(-rng.random((min(4096, steps - k), net.n)))
        rate = lam_max / (1 + np.exp(shift - arriving[k % reach]))
        arriving[k % reach] = 0
        at, end = k * net.dt + uniform[k % 4096] / rate, (k + 1) * net.dt
        early = np.flatnonzero((at < end) & (at < free))  # lost; arrivals have no memory, the next one counts from when the unit is free
        at[early] = free[early] + again.exponential(1 / rate[early])
        fired = np.flatnonzero(at < end)
        while len(fired):
            units.append(fired)
            times.append(at[fired])
            free[fired] = at[fired] + net.refractory
            for d in used:
                arriving[(k + d) % reach] += weight[d][fired].sum(axis=0)
            at[fired] = free[fired] + again.exponential(1 / rate[fired])  # arrivals have no memory
            fired = fired[at[fired] < end]
    if not units:
        return np.empty(0, int), np.empty(0)
    return np.concatenate(units), np.concatenate(times)


def simulate(spark: SparkSession, net: Network, seconds: float, n_datasets: int, seed: int) -> DataFrame:
    """A stream of each data set; t in microseconds."""

    def kernel(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for k in pdf["id"]:
            units, times = _fire(net, seconds, seed * 100_003 + int(k))
            order = np.argsort(times, kind="stable")
            out.append(pd.DataFrame({"stream": str(k), "etype": [str(u) for u in units[order]], "t": (times[order] * TICKS).astype(np.int64), "eid": np.arange(len(order))}))
        return pd.concat(out) if out else pd.DataFrame(columns=["stream", "etype", "t", "eid"])

    return spark.range(0, n_datasets, 1, max(1, n_datasets)).withColumn("k", F.col("id")).groupBy("k").applyInPandas(lambda pdf: kernel(pdf), STREAM)


def refractory(stream: DataFrame, period: int) -> DataFrame:
    """Drop spikes less than `period` after the previous kept one of their (stream, type).

    A gap of at least a period to the spike before always keeps a spike, so that runs without one are thinned apart.
    """
    order = W.partitionBy("stream", "etype").orderBy("t", "eid")
    runs = stream.withColumn("_n", F.sum(F.when(F.col("t") - F.lag("t").over(order) >= period, 1).otherwise(0)).over(order))
    packed = runs.groupBy("stream", "etype", "_n").agg(F.array_sort(F.collect_list(F.struct("t", "eid"))).alias("a"))
    kept = F.aggregate("a", F.slice("a", 1, 0), lambda k, x: F.when((F.size(k) == 0) | (x["t"] - F.element_at(k, -1)["t"] >= period), F.concat(k, F.array(x))).otherwise(k))
    return packed.select("stream", "etype", F.explode(kept).alias("x")).select("stream", "etype", "x.t", "x.eid")


def _uniform(*columns) -> F.Column:
    """[0, 1) by hashing, the same wherever the row is computed."""
    return (F.pmod(F.xxhash64(*columns), F.lit(1 << 53)) / F.lit(float(1 << 53))).cast("double")


def null_stream(spark: SparkSession, model: str, n_channels: int, seconds: float, n_datasets: int, seed: int, low: float = 10.0, high: float = 30.0, groups: int = 5, dt: float = 0.001) -> DataFrame:
    """Independent channels. fixed: a rate each from U[low, high]; shared: `groups` rates; drift: redrawn every 50 steps
    for each channel; tied: redrawn every 50 steps for each of `groups` groups. At most one spike a step."""
    steps = round(seconds / dt)
    ch = F.col("c")
    grid = spark.range(n_datasets).withColumnRenamed("id", "d").select("d", F.explode(F.sequence(F.lit(0), F.lit(n_channels - 1))).alias("c"))
    grid = grid.select("d", "c", F.explode(F.sequence(F.lit(0), F.lit((steps - 1) // 50))).alias("w"))
    who = {"fixed": (ch,), "shared": (ch % groups,), "drift": (ch, F.col("w")), "tied": (ch % groups, F.col("w"))}[model]
    rate = low + (high - low) * _uniform(F.lit(seed), F.lit("rate"), F.col("d"), *who)
    rows = grid.withColumn("rate", rate).select("*", F.explode(F.sequence(F.lit(0), F.lit(49))).alias("i"))
    k = F.col("w") * 50 + F.col("i")
    rows = rows.withColumn("k", k).where(F.col("k") < steps).where(_uniform(F.lit(seed), F.lit("spike"), F.col("d"), ch, F.col("k")) < 1 - F.exp(-F.col("rate") * dt))
    t = ((F.col("k") + _uniform(F.lit(seed), F.lit("at"), F.col("d"), ch, F.col("k"))) * dt * TICKS).cast("long")
    return rows.select(F.col("d").cast("string").alias("stream"), ch.cast("string").alias("etype"), t.alias("t"), (F.col("k").cast("long") * n_channels + ch).alias("eid"))


def null_networks(spark: SparkSession, n: int, c: float, seconds: float, n_datasets: int, seed: int, own: dict[int, float] | None = None) -> DataFrame:
    """Random weights without strong ones, another network for each data set; own: rates of units."""

    def kernel(pdf: pd.DataFrame) -> pd.DataFrame:
        k = int(pdf["id"].iloc[0])
        units, times = _fire(Network(n, random_network(n, 2, c, seed + k), dict(own or {})), seconds, seed * 7919 + k)
        order = np.argsort(times, kind="stable")
        return pd.DataFrame({"stream": str(k), "etype": [str(u) for u in units[order]], "t": (times[order] * TICKS).astype(np.int64), "eid": np.arange(len(order))})

    return spark.range(0, n_datasets, 1, max(1, n_datasets)).withColumn("k", F.col("id")).groupBy("k").applyInPandas(lambda pdf: kernel(pdf), STREAM)
