"""Constants of the spiking network: rates as a sigmoid of the summed input."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def saturation(e_strong: float, dt: float) -> float:
    """The rate at which a step of dt seconds holds a spike with probability e_strong."""
    return -math.log(1 - e_strong) / dt


def displacement(lam_max: float, lam_normal: float) -> float:
    """Shift of the sigmoid that gives lam_normal without input."""
    return math.log(lam_max / lam_normal - 1)


def strong_weight(d: float, beta: float) -> float:
    """Weight of one input that lifts the rate to beta of its maximum."""
    return d + math.log(beta / (1 - beta))


def compensated(lam_normal: float, e_strong: float, alpha: float) -> float:
    """Own rate of a pattern's later members, whose other spikes come from the pattern."""
    return alpha * lam_normal * (1 - e_strong)


def sigmoid_rate(current: Column, lam_max: float, d) -> Column:
    return F.lit(lam_max) / (1 + F.exp(F.lit(d) - current))


def parameters(spark, e_strong: float = 0.95, dt: float = 0.001, lam_normal: float = 20.0, beta: float = 0.9, alpha: float = 1.5, own=None):
    """The derived constants, as column expressions: a row, or one for each of `own` (lam and other columns)."""
    df = spark.createDataFrame([(e_strong, dt, lam_normal, beta, alpha)], "e double, dt double, lam double, beta double, alpha double")
    if own is not None:
        df = own.crossJoin(F.broadcast(df.drop("lam")))
    df = df.withColumn("lam_max", -F.log(1 - F.col("e")) / F.col("dt")).withColumn("d", F.log(F.col("lam_max") / F.col("lam") - 1))
    return df.select(*(own.columns if own is not None else []), F.round("lam_max", 6).alias("lam_max"), F.round("d", 6).alias("displacement"), F.round(F.col("d") + F.log(F.col("beta") / (1 - F.col("beta"))), 6).alias("strong_weight"), F.round(F.col("alpha") * F.col("lam") * (1 - F.col("e")), 6).alias("compensated"))
