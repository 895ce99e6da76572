"""Python functions for SQL and DataFrames: a scalar, a grouped aggregate, a table function, and their registration."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.BooleanType())
def is_subepisode(a: pd.Series, b: pd.Series) -> pd.Series:
    """Whether the types of a occur in b in this order."""

    def inside(x, y) -> bool | None:
        if x is None or y is None:
            return None
        it = iter(y)
        return all(any(u == v for v in it) for u in x)

    return pd.Series([inside(x, y) for x, y in zip(a, b, strict=True)], dtype="object")


@F.pandas_udf(T.LongType())
def similarity_score(a: pd.Series, b: pd.Series) -> pd.Series:
    """How alike two sets of episodes of one size are: 2^i for each common one of size i, as they lose an end at a time."""

    def score(x, y) -> int | None:
        if x is None or y is None:
            return None
        x, y = ({tuple(e) for e in side if e is not None and len(e)} for side in (x, y))
        if len({len(e) for e in x | y}) > 1:
            raise ValueError("episodes of one size are compared")
        total = 0
        while x and y:
            common = x & y
            total += sum(1 << len(e) for e in common)
            x, y = ({part for e in side - common if len(e) > 1 for part in (e[:-1], e[1:])} for side in (x, y))
        return total

    return pd.Series([score(x, y) for x, y in zip(a, b, strict=True)], dtype="Int64")


@F.pandas_udf(T.LongType())
def nonoverlap_count(s: pd.Series, e: pd.Series) -> int:
    """The largest number of disjoint intervals [s, e] among a group's."""
    n, end = 0, None
    for a, b in sorted(zip(s, e, strict=True), key=lambda x: x[1]):
        if end is None or a > end:
            n, end = n + 1, b
    return n


@F.udtf(returnType=T.StructType([T.StructField("ep_id", T.StringType()), T.StructField("freq", T.IntegerType())]))
class EpisodeOccurrences:
    """TABLE(t) PARTITION BY stream ORDER BY t, eid: counts of a serial episode `a>b>c` with gaps in (lo, hi] of each."""

    def __init__(self):
        self.types, self.times, self.spec = [], [], None

    def eval(self, row, spec: str, lo: int, hi: int):
        self.types.append(row["etype"])
        self.times.append(row["t"])
        self.spec = (spec, lo, hi)

    def terminate(self):
        from episodeflow.model import Gap, serial
        from episodeflow.operators.automata import run

        if self.spec:
            types = self.spec[0].split(">")
            gap = Gap(self.spec[1], self.spec[2])
            for _, freq, _peak in run(self.types, self.times, [serial(types, (gap,) * (len(types) - 1))]):
                if freq:
                    yield self.spec[0], freq


def register(spark: SparkSession) -> None:
    """SQL names: is_subepisode, similarity_score, nonoverlap_count, episode_occurrences, parallel_id, serial_id, episode_id.

    episode_id(types, gaps): null gaps for a parallel episode, else the labels of its gaps (empty where there are none).
    """
    spark.udf.register("is_subepisode", is_subepisode)
    spark.udf.register("similarity_score", similarity_score)
    spark.udf.register("nonoverlap_count", nonoverlap_count)
    spark.udtf.register("episode_occurrences", EpisodeOccurrences)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION parallel_id(x ARRAY<STRING>) RETURNS STRING RETURN array_join(array_sort(x), '+')")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION serial_id(x ARRAY<STRING>, gap STRING) RETURNS STRING RETURN array_join(x, concat('-', gap, '->'))")
    joined = "concat(x[0], array_join(transform(slice(x, 2, greatest(size(x) - 1, 0)), (y, i) -> concat(coalesce(concat('-', get(gaps, i)), ''), '->', y)), ''))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION episode_id(x ARRAY<STRING>, gaps ARRAY<STRING>) RETURNS STRING RETURN CASE WHEN gaps IS NULL THEN array_join(array_sort(x), '+') ELSE {joined} END")
