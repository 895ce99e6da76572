"""Candidate generation, as DataFrame plans and, for the small tables of the level loop, as lists."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode, Gap


def parallel_candidates(frequent: DataFrame) -> DataFrame:
    """frequent: types, sorted, all of one size k. Episodes that share k - 1 types are joined; all k-subsets must be frequent."""
    k = F.size("types")
    own = frequent.select("types", F.slice("types", F.lit(1), k - 1).alias("head"), F.element_at("types", -1).alias("last"))
    joined = own.alias("a").join(own.alias("b"), F.col("a.head") == F.col("b.head")).where("a.last < b.last").select(F.concat("a.types", F.array("b.last")).alias("types"))
    size = F.size("types")
    drops = joined.select("types", F.explode(F.transform(F.sequence(F.lit(0), size - 1), lambda i: F.filter("types", lambda x, j: j != i))).alias("sub"))
    found = drops.join(frequent.select(F.col("types").alias("sub")), "sub", "left_semi").groupBy("types").count()
    return found.where(F.col("count") == size).select("types")


def serial_candidates(frequent: DataFrame) -> DataFrame:
    """frequent: types and gaps (labels). Joined where one without its first node is the other without its last, gaps too."""
    a = frequent.select(F.expr("slice(types, 2, size(types) - 1)").alias("kt"), F.expr("if(size(gaps) > 1, slice(gaps, 2, size(gaps) - 1), array())").alias("kg"), F.col("types").alias("at"), F.col("gaps").alias("ag"))
    b = frequent.select(F.expr("slice(types, 1, size(types) - 1)").alias("kt"), F.expr("if(size(gaps) > 1, slice(gaps, 1, size(gaps) - 1), array())").alias("kg"), F.element_at("types", -1).alias("bt"), F.element_at("gaps", -1).alias("bg"))
    return a.join(b, ["kt", "kg"]).select(F.concat("at", F.array("bt")).alias("types"), F.concat("ag", F.array("bg")).alias("gaps"))


def next_parallel(frequent: list[Episode]) -> list[Episode]:
    have = {e.types for e in frequent}
    by_head: dict[tuple, list[str]] = {}
    for t in sorted(have):
        by_head.setdefault(t[:-1], []).append(t[-1])
    out = []
    for head, lasts in by_head.items():
        for a, b in combinations(lasts, 2):
            new = (*head, a, b)
            if all(new[:i] + new[i + 1 :] in have for i in range(len(new) - 2)):
                out.append(Episode("parallel", new))
    return out


def serial_seeds(types: list[str], gaps: list[Gap], allow_self: bool = True) -> list[Episode]:
    return [Episode("serial", (a, b), (g,)) for a in types for b in types if allow_self or a != b for g in gaps]


def next_serial(frequent: list[Episode], prune: str = "ends") -> list[Episode]:
    """ends: prefix and suffix frequent, which is sound for gaps; all: also every other subset, sound without gaps only."""
    by_head: dict[tuple, list[Episode]] = {}
    for e in frequent:
        by_head.setdefault((e.types[:-1], e.gaps[:-1]), []).append(e)
    out = [Episode("serial", (*a.types, b.types[-1]), a.gaps + b.gaps[-1:]) for a in frequent for b in by_head.get((a.types[1:], a.gaps[1:]), [])]
    if prune == "all":
        have = {e.types for e in frequent}
        out = [e for e in out if all(e.types[:i] + e.types[i + 1 :] in have for i in range(len(e.types)))]
    return out
