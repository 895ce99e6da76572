"""Blocks of whole streams against the distributed plans, and what of a stream comes to the driver."""

import os
import random

import pytest
from pyspark.sql import functions as F
from pyspark.sql.classic.dataframe import DataFrame

from episodeflow import queries as own
from episodeflow.model import Gap
from episodeflow.operators import frequency, occurrences, significance
from episodeflow.plans import blocks, miner, orders, recording
from episodeflow.sources import streams
from episodeflow.streaming import online


def _many_streams(spark, n=900, streams=40, ties=False):
    rng = random.Random(11)
    rows = [(f"s{rng.randrange(streams)}", rng.choice("ABCDEF"), rng.randrange(200), 7 if ties else i) for i in range(n)]
    return spark.createDataFrame(rows, "stream string, etype string, t long, eid long")


@pytest.mark.parametrize("plan", [
    miner.EpisodePlan("parallel", 20, expiry=9, max_k=4),
    miner.EpisodePlan("parallel", 20, expiry=9, strict_expiry=True, max_k=3),
    miner.EpisodePlan("parallel", 5, expiry=0),
    miner.EpisodePlan("serial", 15, gaps=(Gap(0, 10),), max_k=4),
    miner.EpisodePlan("serial", 12, gaps=(Gap(0, 4), Gap(6, 20)), max_k=3, allow_self=False),
    miner.EpisodePlan("parallel", 20, expiry=190, max_k=3),
])
def test_blocks_of_streams_count_like_the_distributed_plan(spark, monkeypatch, plan):
    s = _many_streams(spark)
    monkeypatch.setattr(blocks, "BLOCK", 100)
    want = {(e.id, f) for e, f in miner.mine(s, plan, "windowed").rows}
    got = miner.mine(s, plan, "streams")
    assert {(e.id, f) for e, f in got.rows} == want and len(want) > 6
    monkeypatch.setattr(blocks, "MOST", 3)  # a stream that a task can't hold goes the other way
    assert {(e.id, f) for e, f in miner.mine(s, plan, "streams").rows} == want


def test_events_of_one_position_go_the_distributed_way(spark):
    s, plan = _many_streams(spark, ties=True), miner.EpisodePlan("parallel", 10, expiry=9, max_k=3)
    assert {(e.id, f) for e, f in miner.mine(s, plan, "streams").rows} == {(e.id, f) for e, f in miner.mine(s, plan, "windowed").rows}


def test_rare_types_stay_off_the_driver(spark, monkeypatch):
    rows = spark.range(4000).selectExpr("'a' AS stream", "if(id % 2 = 0, 'x', cast(id as string)) AS etype", "id AS t", "id AS eid")
    seen, collect = [], DataFrame.collect
    monkeypatch.setattr(DataFrame, "collect", lambda df: seen.append(collect(df)) or seen[-1])
    found = miner.mine(rows, miner.EpisodePlan("serial", 0.1, gaps=(Gap(0, 10),), max_k=2), "windowed")
    assert [e.id for e, _ in found.rows] == ["x", "x-(0,10]->x"] and found.levels[0][1] == 2001
    assert max(map(len, seen)) == 1


def test_words_of_repeated_documents_are_one_stream(spark, tmp_path):
    docs = [(1, "The cat, the dog"), (1, "the cat"), (2, "a cat the"), (3, None)]
    spark.createDataFrame(docs, "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    assert streams.packed_words(spark, str(tmp_path)) is None
    spark.createDataFrame(docs[1:], "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/b/documents.parquet")
    plan = miner.EpisodePlan("serial", 1, gaps=(Gap(0, 10),), max_k=3)
    s, rows = streams.words(spark, f"{tmp_path}/b"), streams.packed_words(spark, f"{tmp_path}/b")
    assert {(e.id, f) for e, f in miner.mine(s, plan, "streams", rows).rows} == {(e.id, f) for e, f in miner.mine(s, plan, "windowed").rows}


SF = "/root/testdata/sf0.01"


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")
def test_slices_are_counted_without_a_join_of_their_events(spark, tmp_path, monkeypatch):
    ev = spark.read.parquet(f"{SF}/events.parquet")
    for k in range(3):  # ticks of several events
        ev.withColumns({"event_id": F.col("event_id") + 100_000 * k, "user_id": F.col("user_id") + 150 * k}).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    names = ("top_episodes_by_slice", "subepisode_udf", "similarity_burst", "similarity_matrix")
    got = {}
    with monkeypatch.context() as m:
        m.setattr(occurrences, "serial_pairs", None)
        for name in names:
            got[name] = sorted(map(tuple, own.QUERIES[name](spark, str(tmp_path)).collect()))
    monkeypatch.setattr(blocks, "MOST", 0)
    for name in names[:2]:
        assert got[name] == sorted(map(tuple, own.QUERIES[name](spark, str(tmp_path)).collect()))
    assert len(got["similarity_burst"]) == 29 and len(got["similarity_matrix"]) == 841


@pytest.mark.parametrize("ties", [False, True])
@pytest.mark.parametrize("k", [2, 3])
def test_orders_are_counted_chunk_by_chunk(spark, monkeypatch, ties, k):
    s, gap = _many_streams(spark, n=600, streams=6, ties=ties), Gap(0, 200)
    grown = occurrences.serial_pairs(s, gap)
    if k == 3:
        grown = significance._grow_all(grown, s, (gap,))
    want = sorted(map(tuple, frequency.count_by_stream(grown).collect()))
    types = list("ABCDEFG")  # one of them never comes
    for chunk, block, lanes in ((1000, 1 << 18, 1 << 18), (7, 50, 1 << 18), (1, 10, 100)):
        monkeypatch.setattr(orders, "BLOCK", block)
        monkeypatch.setattr(orders, "LANES", lanes)
        assert sorted(map(tuple, orders.count_by_stream(s, types, k, gap, chunk).collect())) == want
    fewer = {x[1] for x in map(tuple, orders.count_by_stream(s, ["A", "B"], k, gap, 7).collect())}
    assert fewer == {x[1] for x in want if set(x[1].split("-(0,200]->")) <= set("AB")}


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")
def test_a_slice_is_held_by_no_task_and_its_events_may_repeat(spark, tmp_path, monkeypatch):
    ev = spark.read.parquet(f"{SF}/events.parquet")
    ev.unionByName(ev.where("event_id % 3 = 0")).write.parquet(f"{tmp_path}/events.parquet")  # events of one position
    monkeypatch.setattr(blocks, "MOST", 3)
    with monkeypatch.context() as m:
        m.setattr(occurrences, "serial_pairs", None)
        got = sorted(map(tuple, own.QUERIES["subepisode_udf"](spark, str(tmp_path)).collect()))
    monkeypatch.setattr(own, "SLICE_TYPES", 0)
    assert got == sorted(map(tuple, own.QUERIES["subepisode_udf"](spark, str(tmp_path)).collect())) and len(got) == 580


def test_bursts_are_found_between_windows(spark):
    rng, rows, want = random.Random(5), [], set()
    for name in "abcdef":
        ticks, at = [], 0
        for _ in range(40):
            at += rng.choice([0, 1, 1, 2, 3, 5, 9])
            ticks.append(at)
        rows += [(name, 60_000_000 * t) for t in ticks]
        runs = [[ticks[0]]]
        for t in ticks[1:]:  # a silence of the whole gap ends a burst
            runs[-1].append(t) if t - runs[-1][-1] < 3 else runs.append([t])
        best = max((r for r in runs if len(r) >= 2), key=lambda r: (len(r), -r[0]))
        want.add((name, 60 * best[0], 60 * best[-1] + 180, len(best)))
    s = spark.createDataFrame(rows, "stream string, t long").select("stream", F.timestamp_micros("t").alias("ts"))
    got = online.densest_burst(s, "3 minutes", 2)
    assert {(r["stream"], r["s"], r["e"], r["n"]) for r in got.select("stream", F.unix_seconds("start").alias("s"), F.unix_seconds("end").alias("e"), "n").collect()} == want
    assert "Sessions" not in got._jdf.queryExecution().executedPlan().toString()  # which sort a stream's events in one task
    assert not online.densest_burst(s.where("false"), "3 minutes", 2).collect()


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")
@pytest.mark.parametrize("name", ["serial_generalised_pairs", "recording_serial_pairs"])
def test_pairs_are_mined_no_further_than_pairs(spark, monkeypatch, name):
    sizes, level = [], miner._level
    monkeypatch.setattr(miner, "_level", lambda r, k, *rest: sizes.append(k) or level(r, k, *rest))
    monkeypatch.setattr(recording, "MOST", 0)
    assert own.QUERIES[name](spark, SF).count() == 22 and sizes == [1, 2]
