"""Counting while events arrive, rates and bursts."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.streaming.stateful_processor import ExpiredTimerInfo, TimerValues

from ..model import Episode
from ..operators.automata import machine

OUT = "stream string, ep_id string, freq long"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


class _Counter(StatefulProcessor):
    """A stream's waiting events, and what each of its episodes remembers.

    Only episodes that an event touches are read and written. Waiting events are read again when some of them are due.
    """

    def __init__(self, episodes: list[Episode], expiry: int | None):
        self.episodes, self.expiry = {e.id: e for e in episodes}, expiry

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.waiting = handle.getListState("waiting", "t long, eid long, etype string")
        self.remembered = handle.getMapState("remembered", "ep_id string", "state string")

    def _wake(self, t: int) -> None:
        self.handle.registerTimer(t // 1000 + 1)

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues: TimerValues) -> Iterator[pd.DataFrame]:
        for pdf in rows:
            new = [(int(t), int(i), x) for t, i, x in zip(pdf["t"], pdf["eid"], pdf["etype"], strict=True)]
            if new:
                self.waiting.appendList(new)
                self._wake(max(min(new)[0], timerValues.getCurrentWatermarkInMs() * 1000))
        return iter(())

    def handleExpiredTimer(self, key: tuple, timerValues: TimerValues, expiredTimerInfo: ExpiredTimerInfo) -> Iterator[pd.DataFrame]:
        mark, held = timerValues.getCurrentWatermarkInMs() * 1000, list(self.waiting.get())
        due = sorted(tuple(x) for x in held if x[0] <= mark)
        if not due:
            return
        held = [tuple(x) for x in held if x[0] > mark]
        if held:
            self.waiting.put(held)
            self._wake(min(held)[0])
        else:
            self.waiting.clear()
        seen, out = {x for _, _, x in due}, []
        for name, e in self.episodes.items():
            if seen.isdisjoint(e.types):
                continue
            m = machine(e, self.expiry)
            if self.remembered.containsKey((name,)):
                m.load(json.loads(self.remembered.getValue((name,))[0]))
            before = m.freq
            for t, _, x in due:
                if x in e.types:
                    m.take(x, t)
            self.remembered.updateValue((name,), (json.dumps(m.dump()),))
            if m.freq != before:
                out.append((key[0], name, m.freq))
        if out:
            yield pd.DataFrame(out, columns=["stream", "ep_id", "freq"])


def online_count(events: DataFrame, episodes: list[Episode], expiry: int | None, late: str = "1 hour") -> DataFrame:
    """Running frequencies for each stream of parallel episodes (within expiry) and of serial ones (by gaps, or expiry).

    events: (stream, etype, ts, t, eid). Events wait until the watermark has passed them and are then taken in order,
    so that the counts equal those of a batch over the same events; later ones are dropped and `late_rows` counts them.
    An episode remembers a latest time for each type, or what of its prefixes is still within reach. The state lies in
    RocksDB, which the session is told to use.
    """
    if any(e.kind == "parallel" for e in episodes) and expiry is None:
        raise ValueError("parallel episodes need an expiry")
    events.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKSDB)
    return events.withWatermark("ts", late).groupBy("stream").transformWithStateInPandas(_Counter(episodes, expiry), OUT, "update", "EventTime")


def late_rows(query: StreamingQuery) -> int:
    """Rows that a query's stateful operators dropped behind the watermark, over the progress it still remembers."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def batch_sink(path: str) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: each batch into a folder of its own, written anew when a batch is repeated."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def closed(events: DataFrame, path: str) -> DataFrame:
    """The events of a replay that takes all of them in one batch, and one far later event of no type, written to `path`.

    It moves the watermark beyond the last events, which otherwise would wait for ever; later times don't fit pandas.
    """
    spark = events.sparkSession
    last = spark.range(1).selectExpr("timestamp'2262-04-01 00:00:00' AS ts")
    last.write.parquet(path)
    late = spark.readStream.schema(last.schema).parquet(path)
    columns = {"stream": F.lit("").alias("stream"), "etype": F.lit("").alias("etype"), "t": F.unix_micros("ts").alias("t"), "eid": F.lit(-1).cast("long").alias("eid"), "ts": F.col("ts")}
    return events.unionByName(late.select(*[columns[c] for c in events.columns]))


def rates(events: DataFrame, width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events of each type in tumbling (or sliding) windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy("stream", "etype", w.alias("w")).count()


def pairs_online(events: DataFrame, lo: str, hi: str, late: str = "1 hour") -> DataFrame:
    """Pairs of events of a stream with the second within (lo, hi] after the first: a join of the stream with itself."""
    a = events.select(F.col("stream").alias("sa"), F.col("etype").alias("a"), F.col("ts").alias("ta"), F.col("eid").alias("ia")).withWatermark("ta", late)
    b = events.select(F.col("stream").alias("sb"), F.col("etype").alias("b"), F.col("ts").alias("tb"), F.col("eid").alias("ib")).withWatermark("tb", late)
    return a.join(b, F.expr(f"sa = sb AND tb > ta + interval {lo} AND tb <= ta + interval {hi}"))


def dedupe_online(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["stream", "etype", "eid"])


def bursts(events: DataFrame, gap: str, min_events: int) -> DataFrame:
    """Sessions that a silence of `gap` ends, with at least min_events events: batch or stream."""
    w = F.session_window("ts", gap)
    return events.groupBy("stream", w.alias("w")).agg(F.count("*").alias("n")).where(F.col("n") >= min_events).select("stream", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def densest_burst(events: DataFrame, gap: str, min_events: int) -> DataFrame:
    """Each stream's burst with the most events; ties: the earliest. A batch only: (stream, start, end, n), as of `bursts`.

    Within a window as wide as the gap no silence can be: events are added up by window, and silences looked for between
    the few windows of a stream, not between its events.
    """
    from pyspark.sql import Window as W

    in_time, order, wait = W.partitionBy("stream").orderBy("start"), W.partitionBy("stream").orderBy(F.desc("n"), "start"), F.expr(f"interval {gap}")
    parts = events.where("ts is not null").groupBy("stream", F.window("ts", gap)).agg(F.min("ts").alias("start"), F.max("ts").alias("last"), F.count("*").alias("n"))
    before = F.lag("last").over(in_time)
    parts = parts.withColumn("_o", F.when(before.isNull() | (F.col("start") >= before + wait), 1).otherwise(0))
    found = parts.withColumn("_b", F.sum("_o").over(in_time)).groupBy("stream", "_b").agg(F.min("start").alias("start"), (F.max("last") + wait).alias("end"), F.sum("n").alias("n"))
    return found.where(F.col("n") >= min_events).withColumn("_r", F.row_number().over(order)).where("_r = 1").select("stream", "start", "end", "n")
