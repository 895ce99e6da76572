"""The registered queries: schemas, SQL beside them, golden counts, plans, sources and streaming."""

import os

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from episodeflow import queries as own
from episodeflow.functions import udfs
from episodeflow.model import Gap, parallel, serial
from episodeflow.operators import frequency, occurrences
from episodeflow.sources import streams as T
from episodeflow.streaming import online

SF = "/root/testdata/sf0.01"
needs_data = pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")


def test_sql_stands_beside_registered_queries():
    assert set(own.SQL) <= set(own.QUERIES)
    assert set(entry.oracle_sql()) <= set(entry.queries())


@needs_data
def test_golden_counts(spark):
    got = {r["ep_id"]: r["freq"] for r in own.QUERIES["parallel_pairs_6h"](spark, SF).collect()}
    assert got == {"click+error": 385, "click+purchase": 376, "click+signup": 361, "click+view": 384, "error+purchase": 345, "error+signup": 358, "error+view": 376, "purchase+signup": 366, "purchase+view": 332, "signup+view": 348}
    got = {r["ep_id"]: r["freq"] for r in own.QUERIES["serial_pairs_fixed"](spark, SF).collect()}
    assert got["click-(0,6h]->click"] == 184 and got["error-(0,6h]->view"] == 208


@needs_data
def test_golden_chain(spark):
    rows = own.QUERIES["chain_mine"](spark, SF).collect()
    sizes = [sum(r["k"] == k for r in rows) for k in range(1, 6)]
    assert sizes == [27, 6, 6, 4, 1]
    longest = [r for r in rows if r["k"] == 5]
    assert longest[0]["freq"] == 168 and longest[0]["ep_id"] == "23-(4,6]->[0 1 2]-(2,4]->3-(6,8]->4-(2,4]->5"


@needs_data
def test_some_queries_match_duckdb(spark):
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for name in ("events", "orders", "customer", "nation", "region", "conversations"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{SF}/{name}.parquet')")
    for name in ("stream_histogram", "serial_interval_sweep", "similarity_matrix", "freq_cube_segment", "conversation_roles", "udtf_occurrences"):
        df = own.QUERIES[name](spark, SF)
        got = con.execute(own.SQL[name])
        columns = [c[0] for c in got.description]
        want = sorted(map(str, got.fetchall()))
        assert sorted(str(tuple(r[c] for c in columns)) for r in df.collect()) == want, name


@needs_data
def test_plans_have_no_product_of_events_and_read_few_columns(spark):
    df = own.QUERIES["serial_pairs_fixed"](spark, SF)
    plan = df._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert "Cartesian" not in plan and "BroadcastNestedLoop" not in plan and "Python" not in plan
    assert "props" not in plan.split("ReadSchema")[1].split("\n")[0]


def test_files_round_trip(spark, tmp_path):
    s = spark.createDataFrame([("a", "x", 5, 1), ("a", "y", 90_000_000_000, 2), ("b", "x", 7, 3)], "stream string, etype string, t long, eid long")
    T.save_stream(s, f"{tmp_path}/p")
    assert sorted(map(tuple, T.read_spikes(spark, f"{tmp_path}/p").collect())) == sorted(map(tuple, s.collect()))
    for fmt in ("orc", "json", "csv"):
        w = s.write.option("header", True) if fmt == "csv" else s.write
        w.format(fmt).save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, T.read_spikes(spark, f"{tmp_path}/{fmt}", fmt).collect())) == sorted(map(tuple, s.collect()))
    s.select(F.concat_ws("\t", "stream", "etype", F.col("t").cast("string"), F.col("eid").cast("string"))).write.text(f"{tmp_path}/text")
    assert T.read_spikes(spark, f"{tmp_path}/text", "text").count() == 3


def test_a_day_that_holds_all_events_is_written_by_many_tasks(spark, tmp_path):
    s = spark.range(4000).selectExpr("'a' AS stream", "'x' AS etype", "id AS t", "id AS eid")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        T.save_stream(s, f"{tmp_path}/p")
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    files = list((tmp_path / "p" / "day=0").glob("*.parquet"))
    assert len(files) > 1 and T.read_spikes(spark, f"{tmp_path}/p").count() == 4000


def test_ticks_do_not_depend_on_the_zone(spark):
    df = spark.sql("SELECT timestamp_ntz'2024-01-01 00:00:01' AS ts, 1 AS id, 'x' AS e")
    spec = T.EventStreamSpec("'a'", "e", "ts", "id")
    want = T.as_stream(df, spec).first()["t"]
    spark.conf.set("spark.sql.session.timeZone", "America/New_York")
    try:
        assert T.as_stream(df, spec).first()["t"] == want == 1_704_067_201_000_000
    finally:
        spark.conf.set("spark.sql.session.timeZone", "UTC")


def test_online_counts_equal_batch_counts(spark, tmp_path):
    rows = [("a", x, 1_700_000_000_000_000 + 60_000_000 * t, t) for t, x in enumerate("ABABBAABCCABACBA")]
    s = spark.createDataFrame(rows, "stream string, etype string, t long, eid long")
    far = spark.createDataFrame([("z", "Z", 1_800_000_000_000_000, 99)], s.schema)
    for k, part in enumerate([s.where("eid < 8"), s.where("eid >= 8"), far]):
        part.coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
    eps = [parallel("AB"), parallel("ABC")]
    ev = spark.readStream.schema(s.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*").withColumn("ts", F.timestamp_micros("t"))
    q = online.online_count(ev, eps, 180_000_000).writeStream.outputMode("update").format("memory").queryName("online_test").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r["ep_id"]: r["freq"] for r in spark.table("online_test").where("stream = 'a'").groupBy("ep_id").agg(F.max("freq").alias("freq")).collect()}
    want = {r["ep_id"]: r["freq"] for r in frequency.count(occurrences.parallel_intervals(occurrences.recents(s, 180_000_000), eps)).collect()}
    assert got == want


@needs_data
def test_replay_counts_the_last_hour_too(spark, tmp_path):
    first = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts").limit(3)
    rows = [(i, 1, k, i) for i, k in enumerate(["click", "purchase", "click", "view", "purchase"])]
    made = spark.createDataFrame(rows, "event_id long, user_id long, event_type string, m int").withColumn("ts", F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, m)")).withColumns({"value": F.lit(0.0), "props": F.lit("{}")})
    made.select(first.columns).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = {r["ep_id"]: r["freq"] for r in own.QUERIES["online_count"](spark, str(tmp_path)).collect()}
    assert got == {"click+purchase": 2, "click+view": 1}
    whole = own.QUERIES["online_count"](spark, SF).groupBy("ep_id").agg(F.sum("freq").alias("freq")).collect()
    batch = frequency.count(occurrences.parallel_pairs(occurrences.recents(T.user_events(spark, SF), 21_600_000_000))).where("ep_id IN ('click+purchase', 'click+view')").collect()
    assert {r["ep_id"]: r["freq"] for r in whole} == {r["ep_id"]: r["freq"] for r in batch}


def test_online_orders_equal_batch_counts_and_late_rows_are_counted(spark, tmp_path):
    import random

    r = random.Random(5)
    rows = [("ab"[k % 2], r.choice("ABCD"), 1_700_000_000_000_000 + 60_000_000 * (k // 3), k) for k in range(240)]
    s = spark.createDataFrame(rows, "stream string, etype string, t long, eid long")
    far = spark.createDataFrame([("z", "Z", 1_800_000_000_000_000, 999)], s.schema)
    tardy = spark.createDataFrame([("a", "A", 1_700_000_000_000_001, 1000)], s.schema)
    for k, part in enumerate([s.where("eid < 100"), s.where("eid >= 100"), far, tardy]):
        part.coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
        for f in (tmp_path / "in" / str(k)).glob("part-*"):
            os.utime(f, (1_700_000_000 + k, 1_700_000_000 + k))
    gap, wide = Gap(0, 180_000_000, "g"), Gap(60_000_000, 300_000_000, "h")
    eps = [serial("AB", (gap,)), serial("ABA", (gap, wide)), serial("AABC", (gap, gap, wide))]
    ev = spark.readStream.schema(s.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*").withColumn("ts", F.timestamp_micros("t"))
    q = online.online_count(ev, eps, None).writeStream.outputMode("update").foreachBatch(online.batch_sink(f"{tmp_path}/out")).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    got = {(x["stream"], x["ep_id"]): x["n"] for x in spark.read.schema(online.OUT).parquet(f"{tmp_path}/out").groupBy("stream", "ep_id").agg(F.max("freq").alias("n")).collect()}
    from episodeflow.operators import automata

    want = {(x["stream"], x["ep_id"]): x["freq"] for x in automata.count_by_stream(s, eps).where("freq > 0").collect()}
    assert got == want and len(want) >= 4
    assert online.late_rows(q) == 1


def test_triggers_modes_and_sinks(spark, tmp_path):
    rows = [("a", x, 1_700_000_000_000_000 + 60_000_000 * t, t) for t, x in enumerate("ABAB")]
    s = spark.createDataFrame(rows, "stream string, etype string, t long, eid long").withColumn("ts", F.timestamp_micros("t"))
    s.coalesce(1).write.parquet(f"{tmp_path}/in")
    live = online.rates(spark.readStream.schema(s.schema).parquet(f"{tmp_path}/in"), "2 minutes")
    for mode, sink in (("update", "memory"), ("complete", "memory"), ("complete", "console")):
        q = live.writeStream.outputMode(mode).format(sink).queryName(f"sink_{mode}_{sink}").option("checkpointLocation", f"{tmp_path}/{mode}-{sink}").trigger(processingTime="1 second").start()
        try:
            q.processAllAvailable()
            assert q.exception() is None
            if sink == "memory":
                assert sum(r["count"] for r in spark.table(f"sink_{mode}_{sink}").collect()) == 4
        finally:
            q.stop()


def test_spikes_as_a_stream_equal_the_batch(spark):
    batch = own.QUERIES["spike_source"](spark, SF).collect()
    assert sorted(map(tuple, own.QUERIES["spike_stream"](spark, SF).collect())) == sorted(map(tuple, batch)) and batch


def test_sql_names(spark):
    udfs.register(spark)
    got = spark.sql("SELECT episode_id(array('b', 'a'), null) AS p, episode_id(array('b', 'a', 'c'), array('(0,2]', '(2,4]')) AS s, episode_id(array('b', 'a'), array()) AS u, episode_id(array('b'), array()) AS o, "
                    "similarity_score(array(array('a','b','c'), array('x','y','z')), array(array('a','b','c'), array('q','x','y'))) AS n, similarity_score(null, array(array('a'))) AS z, similarity_score(array(), array(array('a'))) AS e").first()
    assert (got["p"], got["s"], got["u"], got["o"]) == ("a+b", serial("bac", (Gap(0, 2), Gap(2, 4))).id, serial("ba").id, "b")
    assert (got["n"], got["z"], got["e"]) == (8 + 4, None, 0)


def test_online_rates_pairs_and_dedupe(spark, tmp_path):
    rows = [("a", x, 1_700_000_000_000_000 + 60_000_000 * t, t) for t, x in ((0, "A"), (2, "B"), (2, "B"), (9, "A"), (11, "B"))]
    s = spark.createDataFrame(rows, "stream string, etype string, t long, eid long").withColumn("ts", F.timestamp_micros("t"))
    s.coalesce(1).write.parquet(f"{tmp_path}/in")
    live = spark.readStream.schema(s.schema).parquet(f"{tmp_path}/in")

    def rows_of(df, name, mode):
        q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{tmp_path}/{name}").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name).collect()

    got = rows_of(online.rates(live, "5 minutes"), "rates_test", "complete")
    assert sum(r["count"] for r in got) == 5
    assert len(rows_of(online.dedupe_online(live), "dedupe_test", "append")) == 4
    pairs = rows_of(online.pairs_online(live, "0 minutes", "3 minutes"), "pairs_test", "append")
    assert sorted((r["a"], r["b"], r["ia"], r["ib"]) for r in pairs) == [("A", "B", 0, 2), ("A", "B", 0, 2), ("A", "B", 9, 11)]
    batch = online.densest_burst(s, "3 minutes", 2).collect()
    assert [(r["n"]) for r in batch] == [3]
    sliding = rows_of(online.rates(live, "4 minutes", "2 minutes"), "sliding_test", "complete")
    assert sum(r["count"] for r in sliding) == 10


def test_band_join_is_exact(spark):
    s = spark.createDataFrame([("a", str(i % 3), i * i % 97, i) for i in range(60)], "stream string, etype string, t long, eid long")
    rows = [tuple(r) for r in s.collect()]
    for lo, hi in ((-1, 0), (0, 1), (0, 10), (5, 7), (20, 60)):
        want = sum(lo < b[2] - a[2] <= hi for a in rows for b in rows)
        assert occurrences.band_join(s, s, lo, hi).count() == want
    with pytest.raises(ValueError):
        Gap(-1, 4)
