"""Episodes, gap sets and their canonical ids.

A stream is (stream STRING, etype STRING, t BIGINT, eid BIGINT), t in integer ticks; its order is that of (t, eid).
A parallel episode is its sorted types joined by `+`; a serial one its types joined by `-label->`, where the label names
the gap interval (lo, hi], or by `->` where there is none.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

STREAM = "stream string, etype string, t long, eid long"
POS = "struct<t:bigint,eid:bigint>"


@dataclass(frozen=True)
class Gap:
    """A half-open interval (lo, hi] of ticks between consecutive events; label: how ids name it."""

    lo: int
    hi: int
    label: str = ""

    def __post_init__(self):
        if not 0 <= self.lo < self.hi:
            raise ValueError(f"a gap needs 0 <= lo < hi, not ({self.lo}, {self.hi}]")
        if not self.label:
            object.__setattr__(self, "label", f"({self.lo},{self.hi}]")


def gap_set(gaps: list[Gap]) -> list[Gap]:
    """The candidate intervals, which have to be disjoint."""
    gaps = sorted(gaps, key=lambda g: g.lo)
    for a, b in zip(gaps, gaps[1:], strict=False):
        if b.lo < a.hi:
            raise ValueError(f"intervals {a.label} and {b.label} overlap")
    return gaps


@dataclass(frozen=True)
class Episode:
    kind: str  # parallel or serial
    types: tuple[str, ...]
    gaps: tuple[Gap, ...] = ()

    @property
    def id(self) -> str:
        if self.kind == "parallel":
            return "+".join(self.types)
        labels = [g.label for g in self.gaps] or [""] * (len(self.types) - 1)
        return self.types[0] + "".join(f"-{g}->{x}" if g else f"->{x}" for g, x in zip(labels, self.types[1:], strict=True))

    def prefix(self) -> Episode:
        return Episode(self.kind, self.types[:-1], self.gaps[:-1])

    def suffix(self) -> Episode:
        return Episode(self.kind, self.types[1:], self.gaps[1:])


def parallel(types) -> Episode:
    if len(set(types)) != len(types):
        raise ValueError("the types of a parallel episode are distinct")
    return Episode("parallel", tuple(sorted(types)))


def serial(types, gaps=()) -> Episode:
    if gaps and len(gaps) != len(types) - 1:
        raise ValueError("a serial episode of n types has n - 1 gaps")
    return Episode("serial", tuple(types), tuple(gaps))


def pos(prefix: str = "") -> Column:
    p = f"{prefix}." if prefix else ""
    return F.struct(F.col(f"{p}t").alias("t"), F.col(f"{p}eid").alias("eid"))


_SPREAD, _HALF = 10**18, 5 * 10**17


def packed(place: Column) -> Column:
    """A position (t, eid) as one number of the same order: aggregates of structs are sorted, those of numbers hashed.

    eid has to lie within 5 * 10^17 of zero.
    """
    return place["t"].cast("decimal(19,0)") * F.lit(_SPREAD).cast("decimal(19,0)") + (place["eid"] + F.lit(_HALF)).cast("decimal(19,0)")


def unpacked(number: Column) -> Column:
    low = F.pmod(number, F.lit(_SPREAD).cast("decimal(38,0)"))
    t = F.try_divide(number - low, F.lit(_SPREAD).cast("decimal(38,0)"))
    return F.struct(t.cast("long").alias("t"), (low.cast("long") - F.lit(_HALF)).alias("eid"))


def latest(place: Column) -> Column:
    """The last of a group's positions, as an aggregate that `unpacked` reads."""
    return F.max(packed(place))


def render_chain(episode: Episode) -> str:
    """Compound types already carry brackets: A [B C] D, with the gaps' labels where there are any."""
    out = episode.types[0]
    for k, x in enumerate(episode.types[1:]):
        out += f" -{episode.gaps[k].label}-> {x}" if episode.gaps else f" {x}"
    return out
