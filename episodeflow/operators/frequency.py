"""The largest set of pairwise non-overlapped intervals, and other counts of occurrences.

Taking the interval that ends first, again and again, is optimal. Intervals are those of `occurrences`: one for each end,
with the latest start, so that a later end never has an earlier start.

Short streams: of the intervals with one start all but the first to end are dropped; a start after the previous end opens
an island which the choice can't reach across; islands are folded on their own, in the JVM.

Long streams (`chunk`, in ticks): what the choice does within a chunk of time depends on the last chosen end before it
only, and that matters for the few intervals alone that begin before the chunk. Each chunk is folded once for each of
these cases, wherever its task is; one small row a chunk is then looked at in order. No task holds the intervals of an
episode in a stream, and an episode that never pauses is spread like any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..model import POS

KEY = ("stream", "ep_id")


def undominated(intervals: DataFrame) -> DataFrame:
    """Of the intervals with one start the first to end: a partial and a final aggregate, no sort."""
    extra = [c for c in intervals.columns if c not in (*KEY, "s", "e")]
    if not extra:
        return intervals.groupBy(*KEY, "s").agg(F.min("e").alias("e"))
    kept = intervals.groupBy(*KEY, "s").agg(F.min(F.struct("e", *extra)).alias("x"))
    return kept.select(*KEY, "s", "x.e", *[f"x.{c}" for c in extra])


def islands(intervals: DataFrame) -> DataFrame:
    """Adds the island within (stream, ep_id): the end of the interval that opens it."""
    order = W.partitionBy(*KEY).orderBy("e")
    before = F.lag("e").over(order)
    opens = intervals.withColumn("_o", F.when(before.isNull() | (F.col("s") > before), F.col("e")))
    return opens.withColumn("island", F.max("_o").over(order)).drop("_o")


def chunk_of(ticks: int, n: int, span: int | None, most: int = 1 << 16, events: int = 512) -> int:
    """A chunk for a stream of n events over so many ticks: many spans, some events, and not more than `most` chunks."""
    return max(64 * (span or 0), -(-ticks // most), ticks * events // max(1, n), 1)


def _nothing() -> Column:
    return F.lit(None).cast(POS)


def _after(item: Column, end: Column) -> Column:
    return end.isNull() | (item["s"] > end)


def _fold(items: Column, end: Column) -> Column:
    """(end, n): the last chosen end and how many were chosen, from the last end before."""
    first = F.struct(end.alias("e"), F.lit(0).cast("bigint").alias("n"))
    return F.aggregate(items, first, lambda a, x: F.when(_after(x, a["e"]), F.struct(x["e"].alias("e"), (a["n"] + 1).alias("n"))).otherwise(a))


def _chunks(intervals: DataFrame, chunk: int) -> DataFrame:
    """(stream, ep_id, _c, all): a chunk's intervals by end; extra columns go along in them."""
    extra = [c for c in intervals.columns if c not in (*KEY, "s", "e")]
    rows = intervals.withColumn("_c", F.floor(F.col("e.t") / chunk))
    return rows.groupBy(*KEY, "_c").agg(F.array_sort(F.collect_list(F.struct("e", "s", *extra))).alias("all"))


def _tables(chunks: DataFrame, chunk: int) -> DataFrame:
    """(stream, ep_id, tables): for each chunk in order the starts of the intervals that begin before it (`heads`), and what
    is chosen where the first k of them are out of reach, for k = 0, 1, ... (`outs`)."""
    heads = F.transform(F.filter("all", lambda x: x["s"]["t"] < F.col("_c") * chunk), lambda x: x["s"])
    rows = chunks.withColumn("_h", heads)
    outs = F.transform(F.sequence(F.lit(0), F.size("_h")), lambda k: _fold(F.slice("all", k + 1, F.size("all")), _nothing()))
    rows = rows.select(*KEY, F.struct("_c", F.col("_h").alias("heads"), outs.alias("outs")).alias("x"))
    return rows.groupBy(*KEY).agg(F.array_sort(F.collect_list("x")).alias("tables"))


def _way(table: Column, end: Column) -> Column:
    """What the table's chunk chooses after `end`."""
    return F.get(table["outs"], F.when(end.isNull(), 0).otherwise(F.size(F.filter(table["heads"], lambda s: s <= end))))


def count_by_stream(intervals: DataFrame, chunk: int | None = None) -> DataFrame:
    """(stream, ep_id, freq)."""
    if chunk is not None:
        first = F.struct(_nothing().alias("e"), F.lit(0).cast("bigint").alias("n"))

        def step(a: Column, x: Column) -> Column:
            got = _way(x, a["e"])
            return F.struct(F.coalesce(got["e"], a["e"]).alias("e"), (a["n"] + got["n"]).alias("n"))

        return _tables(_chunks(intervals, chunk), chunk).select(*KEY, F.aggregate("tables", first, step, lambda a: a["n"]).alias("freq"))
    intervals = intervals.repartition(*KEY)  # the one shuffle: all that follows is clustered by these
    cut = islands(undominated(intervals)).groupBy(*KEY, "island").agg(F.count("*").alias("m"), F.array_sort(F.collect_list(F.struct("e", "s"))).alias("all"))
    freq = F.when(F.col("m") <= 2, F.lit(1).cast("bigint")).otherwise(_fold(F.col("all"), _nothing())["n"])
    return cut.select(*KEY, freq.alias("f")).groupBy(*KEY).agg(F.sum("f").alias("freq"))


def count(intervals: DataFrame, chunk: int | None = None) -> DataFrame:
    """(ep_id, freq), summed over streams: occurrences never cross streams."""
    return count_by_stream(intervals, chunk).groupBy("ep_id").agg(F.sum("freq").alias("freq"))


def _chosen(items: Column, end: Column) -> Column:
    """The items that are chosen after `end`."""

    def step(a: Column, x: Column) -> Column:
        last = F.when(F.size(a) > 0, F.element_at(a, -1)["e"]).otherwise(end)
        return F.when(_after(x, last), F.concat(a, F.array(x))).otherwise(a)

    return F.aggregate(items, F.slice(items, 1, 0), step)


def select_disjoint(intervals: DataFrame, chunk: int | None = None) -> DataFrame:
    """The chosen intervals themselves, numbered within (stream, ep_id) by occ_no; members and other columns go along."""
    extra = [c for c in intervals.columns if c not in ("stream", "ep_id", "s", "e")]
    fields = ["x.s", "x.e", *[f"x.{c}" for c in extra]]
    if chunk is not None:
        chunks = _chunks(intervals, chunk)
        kind = f"struct<e:{POS},n:bigint,out:array<struct<_c:bigint,e:{POS},n:bigint>>>"
        first = F.struct(_nothing().alias("e"), F.lit(0).cast("bigint").alias("n"), F.array().alias("out")).cast(kind)

        def step(a: Column, x: Column) -> Column:
            got = _way(x, a["e"])
            here = F.struct(x["_c"].alias("_c"), a["e"].alias("e"), a["n"].alias("n"))
            return F.struct(F.coalesce(got["e"], a["e"]).alias("e"), (a["n"] + got["n"]).alias("n"), F.concat(a["out"], F.array(here)).alias("out")).cast(kind)

        enters = _tables(chunks, chunk).select(*KEY, F.inline(F.aggregate("tables", first, step, lambda a: a["out"]))).withColumnsRenamed({"e": "_end", "n": "_before"})
        each = chunks.join(enters, [*KEY, "_c"]).select(*KEY, "_before", F.posexplode(_chosen(F.col("all"), F.col("_end"))).alias("i", "x"))
        return each.select(*KEY, *fields, (F.col("_before") + F.col("i") + 1).alias("occ_no"))
    item = F.struct("e", "s", *extra)
    cut = islands(undominated(intervals.repartition(*KEY))).groupBy(*KEY, "island").agg(F.array_sort(F.collect_list(item)).alias("all"))
    chosen = cut.select(*KEY, F.explode(F.when(F.size("all") <= 2, F.slice("all", 1, 1)).otherwise(_chosen(F.col("all"), _nothing()))).alias("x")).select(*KEY, *fields)
    return chosen.withColumn("occ_no", F.row_number().over(W.partitionBy(*KEY).orderBy("e")).cast("long"))


def window_count(intervals: DataFrame, width: int) -> DataFrame:
    """How many windows [w, w + width) of integer start hold the episode: the union of the start ranges of its intervals."""
    fits = undominated(intervals).where(F.col("e.t") - F.col("s.t") < width)
    ranges = fits.select("stream", "ep_id", (F.col("e.t") - width + 1).alias("lo"), F.col("s.t").alias("hi"))
    seen = W.partitionBy("stream", "ep_id").orderBy("hi", "lo").rowsBetween(W.unboundedPreceding, -1)
    new = F.greatest(F.lit(0).cast("long"), F.col("hi") - F.greatest("lo", F.coalesce(F.max("hi").over(seen) + 1, F.col("lo"))) + 1)
    return ranges.withColumn("n", new).groupBy("ep_id").agg(F.sum("n").alias("windows"))
