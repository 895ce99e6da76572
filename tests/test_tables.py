"""Queries that once made up their data follow the given table."""

import pytest
from pyspark.sql import functions as F

from episodeflow import queries as own


@pytest.fixture(scope="module")
def made(spark, tmp_path_factory):
    """Two types; even users fire three times as often as odd ones."""
    path = tmp_path_factory.mktemp("made")
    ev = spark.range(2080).selectExpr("id AS event_id", "timestamp_ntz'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, 20 * id) AS ts", "if(id % 4 = 0, 2 * (id div 4 % 13) + 1, 2 * (id % 13)) AS user_id", "if(id % 2 = 0, 'a', 'b') AS event_type")
    ev.withColumns({"value": F.lit(0.0), "props": F.lit("{}")}).coalesce(1).write.parquet(f"{path}/events.parquet")
    return str(path)


def test_combinations_follow_the_types(spark, made):
    assert sorted(map(tuple, own.QUERIES["combinations_by_size"](spark, made).collect())) == [(k, 2**k) for k in range(1, 7)]


def test_parameters_follow_the_rates(spark, made):
    rows = {int(r["unit"]): r for r in own.QUERIES["rate_parameters"](spark, made).collect()}
    assert len(rows) == 26
    assert all(rows[k]["lam"] > 2 * rows[1]["lam"] and rows[k]["displacement"] < rows[1]["displacement"] for k in range(0, 26, 2))


def test_simulated_units_fire_at_the_rates_of_the_events(spark, made):
    n = {}
    for r in own.QUERIES["spike_source"](spark, made).collect():
        n[int(r["etype"])] = n.get(int(r["etype"]), 0) + r["n"]
    even, odd = (sum(n.get(k, 0) for k in range(4 + p, 26, 2)) for p in (0, 1))
    assert even > 2 * odd > 0
