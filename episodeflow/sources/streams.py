"""Given tables, files and overlays as event streams."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import STREAM

MICRO = "timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', cast({} as timestamp_ntz))"
DAY = "datediff(cast({} as date), date'1970-01-01')"
#: Ticks of one paper millisecond on 10,000 events of the events table; the rate scales with the table.
UNIT_TIMES_EVENTS = 135_000_000 * 10_000


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


@dataclass(frozen=True)
class EventStreamSpec:
    """SQL expressions for a stream's columns; unit: micros (a timestamp), days (a date), ticks (an integer)."""

    stream: str
    etype: str
    time: str
    tiebreak: str
    unit: str = "micros"


def as_stream(df: DataFrame, spec: EventStreamSpec) -> DataFrame:
    t = {"micros": MICRO.format(spec.time), "days": DAY.format(spec.time), "ticks": spec.time}[spec.unit]
    return df.selectExpr(f"cast({spec.stream} as string) as stream", f"cast({spec.etype} as string) as etype", f"cast({t} as bigint) as t", f"cast({spec.tiebreak} as bigint) as eid").where("etype is not null and t is not null")


def user_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_stream(load(spark, sf_dir, "events"), EventStreamSpec("user_id", "event_type", "ts", "event_id"))


def channels(spark: SparkSession, sf_dir: str, m: int = 26) -> DataFrame:
    """One stream in which user_id modulo m is the channel."""
    return as_stream(load(spark, sf_dir, "events"), EventStreamSpec("'all'", f"user_id % {m}", "ts", "event_id"))


def unit(spark: SparkSession, sf_dir: str) -> int:
    return UNIT_TIMES_EVENTS // max(1, load(spark, sf_dir, "events").count())


#: Fixed values of the planted overlay: (index, channel, delay in units).
PLANTED = ((0, 23, 0), (1, 0, 5), (2, 1, 5), (3, 2, 5), (4, 3, 8), (5, 4, 15), (6, 5, 18))
EVERY, JITTER_US, KEEP_FROM = 40, 1_000_000, 5


def overlay(spark: SparkSession, sf_dir: str, u: int, seed: int = 0) -> DataFrame:
    """The channel stream with a pattern planted at every 40th event: unequal delays, jitter, 95 % transmission."""
    base = channels(spark, sf_dir)
    nodes = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(c).alias("c"), F.lit(d).cast("long").alias("d")) for i, c, d in PLANTED]))
    j = F.expr(f"eid div {EVERY}")
    rows = base.where(F.col("eid") % EVERY == 0).withColumn("j", j).withColumn("n", nodes).select("*", "n.*")
    rows = rows.where((F.col("j") * 37 + F.col("i") * 11 + seed) % 100 >= KEEP_FROM)
    t = F.col("t") + F.col("d") * u + ((F.col("j") * 53 + F.col("i") * 29 + seed * 7) % 61 - 30) * JITTER_US
    return base.unionByName(rows.select("stream", F.col("c").cast("string").alias("etype"), t.cast("long").alias("t"), (F.lit(10**9) + 10 * F.col("j") + F.col("i")).cast("long").alias("eid")))


def _words() -> Column:
    return F.split(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}]+")


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as streams of lower-cased words, runs of letters of any script; position is the tick."""
    docs = load(spark, sf_dir, "documents").select("doc_id", _words().alias("w"))
    rows = docs.select("doc_id", F.posexplode("w").alias("t", "etype")).where("etype <> ''")
    return as_stream(rows, EventStreamSpec("doc_id", "etype", "t", "t", "ticks"))


def packed_words(spark: SparkSession, sf_dir: str) -> DataFrame | None:
    """The words as an array for each document, for blocks.encode; none where documents share a doc_id, and so a stream."""
    docs = load(spark, sf_dir, "documents").where("doc_id is not null")
    if not docs.groupBy("doc_id").count().where("count > 1").isEmpty():
        return None
    return docs.select(F.col("doc_id").cast("string").alias("stream"), _words().alias("etypes"))


def co_firing(spark: SparkSession, sf_dir: str, threshold: float) -> DataFrame:
    """Embeddings as a 64-channel array: dimension i fires at tick vec_id where its component is above the threshold."""
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x")).where(F.col("x") > threshold)
    return as_stream(rows, EventStreamSpec("'all'", "lpad(cast(i as string), 2, '0')", "vec_id", "i", "ticks"))


def merge_streams(*streams: DataFrame) -> DataFrame:
    out = streams[0]
    for s in streams[1:]:
        out = out.unionByName(s)
    return out


def slice_time(df: DataFrame, t0: int, t1: int, column: str = "t") -> DataFrame:
    """Events of [t0, t1): a range on the raw column, which reaches the scan."""
    return df.where((F.col(column) >= t0) & (F.col(column) < t1))


def keep_types(stream: DataFrame, types: DataFrame) -> DataFrame:
    """Events whose type is in `types` (column etype)."""
    return stream.join(types.select("etype").distinct(), "etype", "left_semi").select("stream", "etype", "t", "eid")


def dedupe(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicates(["stream", "etype", "t"])


def save_stream(stream: DataFrame, path: str, per_file: int = 1_000_000, day_ticks: int = 86_400_000_000) -> None:
    """Partitioned by day, sorted within files by stream and time, so that slices prune and streams lie together.

    Tasks write ranges of (day, stream, time): a day, or a stream, that holds most events is written by many of them.
    """
    days = stream.withColumn("day", F.floor(F.col("t") / day_ticks).cast("int"))
    days.repartitionByRange("day", "stream", "t").sortWithinPartitions("day", "stream", "t", "eid").write.option("maxRecordsPerFile", per_file).partitionBy("day").mode("overwrite").parquet(path)


def read_spikes(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """A saved stream in parquet, orc, json, csv or text (tab-separated) form."""
    if fmt == "text":
        parts = F.split("value", "\t")
        return spark.read.text(path).select(parts[0].alias("stream"), parts[1].alias("etype"), parts[2].cast("long").alias("t"), parts[3].cast("long").alias("eid"))
    reader = spark.read.schema(STREAM)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path).select("stream", "etype", "t", "eid")

