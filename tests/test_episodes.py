"""Worked sequences, the definitions' invariants, and agreement of all ways of counting with brute force."""

import os
import random
from itertools import combinations, product

import numpy as np
import pytest
from pyspark.sql import functions as F

from episodeflow.functions import rates
from episodeflow.model import STREAM, Episode, Gap, gap_set, parallel, serial
from episodeflow.operators import automata, baselines, candidates, compound, frequency, measures, occurrences, significance, simulator
from episodeflow.plans import recording, strategy
from episodeflow.plans.miner import EpisodePlan, maximal_ids, mine


def seq(text):
    """`A1 B3` as types and times."""
    items = [(x[0], int(x[1:])) for x in text.split()]
    return [x for x, _ in items], [t for _, t in items]


def frame(spark, *sequences):
    rows = [(str(k), x, t, i) for k, (types, times) in enumerate(sequences) for i, (x, t) in enumerate(zip(types, times))]
    return spark.createDataFrame(rows, STREAM)


def freqs(df):
    return {r["ep_id"]: r["freq"] for r in df.collect()}


F_A, F_B = seq("A1 B3 D4 C6 A12 E14 B15"), seq("A1 A2 B4 A5 C10 B12 C13 D17")
GAPS_B = (Gap(0, 5), Gap(5, 10), Gap(0, 5))


def test_seven_events(spark):
    s = frame(spark, F_A)
    assert freqs(strategy.count(s, [serial("ABC"), serial("AB")])) == {"A->B->C": 1, "A->B": 2}
    assert freqs(strategy.count(s, [parallel("AB")], 2)) == {"A+B": 1}
    assert freqs(strategy.count(s, [parallel("AB"), parallel("ABC")], 5)) == {"A+B": 2, "A+B+C": 1}
    assert freqs(strategy.count(s, [parallel("AB")], 3)) == {"A+B": 2}


def test_eight_events(spark):
    s, e = frame(spark, F_B), serial("ABCD", GAPS_B)
    got = occurrences.serial_intervals(s, [e]).collect()
    assert [(r["s"]["t"], r["e"]["t"]) for r in got] == [(2, 17)]
    assert freqs(strategy.count(s, [e])) == {e.id: 1}
    for latest in (False, True):
        assert freqs(automata.naive_count(s, [e], latest)) == {e.id: 0}
    assert automata.run(*F_B, [e])[0][1] == 1
    tracked = compound.track(s, [e]).first()
    assert [(m["etype"], m["t"]) for m in tracked["members"]] == [("A", 2), ("B", 4), ("C", 13), ("D", 17)]


def test_subset_pruning_is_unsound_with_gaps(spark):
    s = frame(spark, seq("A0 B4 C8 A20 B24 C28"))
    g = Gap(0, 5)
    assert freqs(strategy.count(s, [serial("ABC", (g, g))])) == {"A-(0,5]->B-(0,5]->C": 2}
    assert freqs(strategy.count(s, [serial("AC", (g,))])) == {}
    pairs = [serial("AB", (g,)), serial("BC", (g,))]
    assert [e.id for e in candidates.next_serial(pairs)] == ["A-(0,5]->B-(0,5]->C"]
    assert candidates.next_serial(pairs, "all") == []


def test_ties(spark):
    s = frame(spark, seq("A1 B1 A2 B2"))
    g = (Gap(0, 1),)
    assert freqs(strategy.count(s, [parallel("AB")], 0)) == {"A+B": 2}
    assert freqs(frequency.count(occurrences.parallel_pairs(occurrences.recents(s, 0)))) == {"A+B": 2}
    assert freqs(strategy.count(s, [serial("AB", g), serial("AA", g)])) == {"A-(0,1]->B": 1, "A-(0,1]->A": 1}


def test_candidates_join_needs_equal_intervals(spark):
    a, b = Gap(0, 5), Gap(5, 10)
    assert [e.id for e in candidates.next_serial([serial("AB", (a,)), serial("BC", (b,))])] == ["A-(0,5]->B-(5,10]->C"]
    df = spark.createDataFrame([(["A", "B"], ["x"]), (["B", "C"], ["y"])], "types array<string>, gaps array<string>")
    assert [tuple(r) for r in candidates.serial_candidates(df).collect()] == [(["A", "B", "C"], ["x", "y"])]
    two = spark.createDataFrame([(["A", "B", "C"], ["x", "y"]), (["B", "C", "D"], ["x", "z"])], "types array<string>, gaps array<string>")
    assert candidates.serial_candidates(two).count() == 0
    with pytest.raises(ValueError):
        gap_set([Gap(0, 5), Gap(4, 8)])


def test_parallel_candidates_agree(spark):
    rng = random.Random(4)
    for k in (1, 2, 3):
        eps = [parallel(c) for c in combinations("ABCDEF", k) if rng.random() < 0.8]
        df = spark.createDataFrame([(list(e.types),) for e in eps], "types array<string>")
        want = {c for c in combinations("ABCDEF", k + 1) if all(tuple(x for x in c if x != y) in {e.types for e in eps} for y in c)}
        assert {tuple(r[0]) for r in candidates.parallel_candidates(df).collect()} == want
        assert {e.types for e in candidates.next_parallel(eps)} == want


def test_rate_constants(spark):
    lam = rates.saturation(0.95, 0.001)
    d = rates.displacement(lam, 20)
    assert (round(lam, 6), round(d, 6), round(rates.strong_weight(d, 0.9), 6), rates.compensated(20, 0.95, 1.5)) == (2995.732274, 5.002513, 7.199738, pytest.approx(1.5))


def test_similarity(spark):
    def sim(a, b, n):
        df = spark.createDataFrame([("a", list(x)) for x in a] + [("b", list(x)) for x in b], "slice string, types array<string>")
        return {(r["a"], r["b"]): r["sim"] for r in measures.peel_similarity(df, n).collect()}

    assert sim(["abc"], ["abc"], 3)["a", "b"] == 8
    got = sim(["abc", "xyz"], ["abc", "bxy"], 3)
    assert got["a", "b"] == got["b", "a"] == 12
    assert got["a", "a"] == got["b", "b"] == 16
    twice = spark.createDataFrame([("a", list("ab")), ("a", list("ab")), ("b", list("ab")), ("b", list("ab"))], "slice string, types array<string>")
    assert {r["sim"] for r in measures.peel_similarity(twice, 2, multiset=True).collect()} == {8}
    assert {r["sim"] for r in measures.peel_similarity(twice, 2).collect()} == {4}


def test_similarity_of_lists_needs_no_join_of_episodes(spark):
    rng = random.Random(3)
    rows = [(x, [rng.choice("ABC") for _ in range(3)]) for x in "abcd" for _ in range(9)]
    df = spark.createDataFrame(rows, "slice string, types array<string>")
    lists = df.groupBy("slice").agg(F.collect_list("types").alias("sets"))
    got = measures.peel_lists(lists, 3)
    want = sorted(map(tuple, measures.peel_similarity(df, 3).collect()))
    assert sorted(map(tuple, got.collect())) == want and len({x[2] for x in want}) > 3
    pairs = spark.createDataFrame([("a", "b"), ("c", "nobody")], "a string, b string")
    assert sorted(map(tuple, measures.peel_lists(lists, 3, pairs).collect())) == [next(x for x in want if x[:2] == ("a", "b")), ("c", "nobody", 0)]
    text = measures.peel_lists(spark.createDataFrame([("a", [["A"]])], lists.schema), 3)._jdf.queryExecution().executedPlan().toString()
    assert text.count("Join") == 1 and "hashpartitioning" not in text and len(text) < 20_000


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="no test data")
def test_slices_are_compared_a_row_a_pair(spark, monkeypatch):
    from episodeflow import queries

    monkeypatch.setattr(measures, "peel_similarity", None)
    df = queries.QUERIES["similarity_matrix"](spark, "/root/testdata/sf0.001")
    assert df._jdf.queryExecution().executedPlan().toString().count("Join") == 1 and df.count() == 576


def test_every_way_agrees_with_brute_force(spark):
    rng = random.Random(7)
    sequences = []
    for _ in range(60):
        t, times = 0, []
        for _ in range(22):
            t += rng.choice([0, 0, 1, 1, 2, 4])
            times.append(t)
        sequences.append(([rng.choice("ABC") for _ in times], times))
    s = frame(spark, *sequences)
    g, h = Gap(0, 2), Gap(2, 5)
    groups = {
        3: [parallel("AB"), parallel("ABC")],
        0: [parallel("AB")],
        None: [serial("AB", (g,)), serial("AA", (h,)), serial("ABA", (g, h)), serial("ABC", (h, g)), serial("AAA", (g, g))],
        6: [serial("AB"), serial("ABA"), serial("AA")],
    }
    for expiry, eps in groups.items():
        want = {}
        for e in eps:
            want[e.id] = sum(baselines.brute_force_frequency(x, t, e, expiry) for x, t in sequences)
        assert freqs(strategy.count(s, eps, expiry)) == {k: v for k, v in want.items() if v}, expiry
        assert freqs(automata.count(s, eps, expiry)) == {k: v for k, v in want.items() if v}, expiry
        raw = occurrences.serial_intervals(s, eps) if eps[0].gaps else None
        if raw is not None:
            for chunk in (3, 10, 1000):
                assert freqs(frequency.count(raw, chunk)) == {k: v for k, v in want.items() if v}
        if expiry == 0:
            assert freqs(strategy.count(s, eps, 0, "ticks")) == {k: v for k, v in want.items() if v}


def test_general_order_holds_both_kinds():
    rng = random.Random(3)
    for _ in range(200):
        t, times = 0, []
        for _ in range(20):
            t += rng.choice([0, 1, 1, 3])
            times.append(t)
        types = [rng.choice("ABC") for _ in times]
        for expiry in (4, 9):
            assert automata.run_order(types, times, list("ABC"), [], expiry) == baselines.brute_force_frequency(types, times, parallel("ABC"), expiry)
            assert automata.run_order(types, times, list("ABA"), [(0, 1), (1, 2)], expiry) == baselines.brute_force_frequency(types, times, serial("ABA"), expiry)


def test_mining_equals_exhaustive_counting(spark):
    rng = random.Random(2)
    types, times = [rng.choice("ABCDE") for _ in range(400)], [3 * i + rng.choice([0, 1, 2]) for i in range(400)]
    s = frame(spark, (types, times))
    found = mine(s, EpisodePlan("parallel", 10, expiry=12), "windowed")
    for k in (2, 3):
        want = {i: f for i, f in freqs(baselines.enumerate_all(s, "parallel", k, expiry=12)).items() if f >= 10}
        assert {e.id: f for e, f in found.rows if len(e.types) == k} == want
    gaps = (Gap(0, 6), Gap(6, 12))
    deep = mine(s, EpisodePlan("serial", 8, gaps=gaps, max_k=3), "windowed")
    eps = [serial(t, g) for k in (2, 3) for t in product("ABCDE", repeat=k) for g in product(gaps, repeat=k - 1)]
    want = {i: f for i, f in freqs(automata.count(s, eps)).items() if f >= 8}
    assert {e.id: f for e, f in deep.rows if len(e.types) > 1} == want
    by_id = {e.id: f for e, f in deep.rows}
    for e, f in deep.rows:
        if len(e.types) > 2:
            assert f <= min(by_id[e.prefix().id], by_id[e.suffix().id])
    assert maximal_ids([parallel("AB"), parallel("A"), parallel("B"), parallel("C")]) == {"A+B", "C"}


def test_both_strategies_find_the_same(spark):
    rng = random.Random(8)
    sequences = []
    for _ in range(5):
        t, times = rng.randrange(50), []
        for _ in range(250):
            t += rng.choice([0, 0, 1, 2, 4])
            times.append(t)
        sequences.append(([rng.choice("ABCDE") for _ in times], times))
    s = frame(spark, *sequences)
    plans = [
        EpisodePlan("parallel", 12, expiry=5),
        EpisodePlan("parallel", 12, expiry=0),
        EpisodePlan("parallel", 0.02, expiry=4, strict_expiry=True, max_k=3),
        EpisodePlan("serial", 25, gaps=(Gap(0, 3), Gap(3, 6)), max_k=3),
        EpisodePlan("serial", 20, gaps=(Gap(2, 5),), allow_self=False),
        EpisodePlan("serial", 20, gaps=(Gap(0, 2), Gap(40, 44)), max_k=3, prune="all"),
    ]
    for plan in plans:
        a, b = mine(s, plan, "windowed"), mine(s, plan, "recording")
        assert sorted((e.id, f) for e, f in a.rows) == sorted((e.id, f) for e, f in b.rows) and len(a.rows) > 5, plan
        assert [x[:5] for x in a.levels] == [x[:5] for x in b.levels], plan
        assert a.largest() == b.largest() and a.maximal() == b.maximal()
    with pytest.raises(ValueError):
        mine(s, EpisodePlan("serial", 5), "recording")


def test_thresholds():
    assert EpisodePlan("parallel", 0.01, expiry=1).least(25_000) == 250
    assert EpisodePlan("parallel", 300, expiry=1, strict_threshold=True).least(9) == 301
    assert EpisodePlan("serial", 0).least(9) == 1
    assert EpisodePlan("serial", 5, gaps=(Gap(0, 1),)).sound_prune() == "ends" and EpisodePlan("serial", 5).sound_prune() == "all"


def test_empty_and_null_events(spark):
    empty = frame(spark)
    assert mine(empty, EpisodePlan("parallel", 1, expiry=5)).rows == []
    assert mine(empty, EpisodePlan("serial", 1, gaps=(Gap(0, 5),))).rows == []
    assert strategy.count(empty, [serial("AB", (Gap(0, 5),))]).count() == 0


def test_window_frequency(spark):
    types, times = seq("A1 B3 A10 B11 B30")
    s, width = frame(spark, (types, times)), 5
    got = {r["ep_id"]: r["windows"] for r in frequency.window_count(occurrences.parallel_pairs(occurrences.recents(s, width - 1)), width).collect()}
    want = sum(1 for w in range(-10, 40) if {x for x, t in zip(types, times) if w <= t < w + width} == {"A", "B"})
    assert got == {"A+B": want}


def test_rewriting(spark):
    s = frame(spark, seq("A0 B2 C9 A20 B20 C29"))
    occs = compound.track(s, [parallel("AB")], 3)
    rows = sorted((r["t"], r["etype"], r["eid"]) for r in compound.rewrite(s, occs).collect())
    assert rows == [(1, "[A B]", 0), (9, "C", 2), (20, "[A B]", 3), (29, "C", 5)]
    assert compound.rewrite(s, occs, mode="augment").count() == 8
    for strategy in ("windowed", "recording"):
        groups, _, chains = compound.mine_chain(s, EpisodePlan("parallel", 2, expiry=3), EpisodePlan("serial", 2, gaps=(Gap(7, 10),)), strategy=strategy)
        assert "[A B]-(7,10]->C" in {e.id for e, _ in chains.rows}
    rng = random.Random(3)
    many = frame(spark, *[([rng.choice("ABCD") for _ in range(80)], sorted(rng.randrange(200) for _ in range(80))) for _ in range(3)])
    eps = [parallel("AB"), parallel("BCD")]
    for anchor in ("midpoint", "mean"):
        for mode in ("replace", "augment", "types"):
            want = compound.rewrite(many, compound.track(many, eps, 3), anchor, mode)
            assert sorted(map(tuple, recording.rewritten(many, eps, 3, anchor, mode).collect())) == sorted(map(tuple, want.collect()))


def test_arrivals_of_a_step_are_those_of_a_process_with_dead_time():
    for period in (0.0, 0.0003, 0.001):
        units, times = simulator._fire(simulator.Network(50, lam_normal=900.0, refractory=period), 10, 3)
        assert len(units) / 500 == pytest.approx(1 / (1 / 900 + period), rel=0.01)
        for u in range(50):
            assert (np.diff(np.sort(times[units == u])) >= period - 1e-12).all()


def test_refractory(spark):
    types, times = seq("A0 A1 A2 A4 A5 B1 A9")
    got = sorted(r["t"] for r in simulator.refractory(frame(spark, (types, times)), 2).where("etype = 'A'").collect())
    assert got == [0, 2, 4, 9]


def test_planted_order_is_recovered(spark):
    net = simulator.plant(simulator.Network(16, simulator.random_network(16, 2, 0.5, 1)), [[i] for i in range(5)])
    s = simulator.simulate(spark, net, 12, 1, 3).cache()
    found = mine(s, EpisodePlan("serial", 60, gaps=(Gap(4000, 6000),), max_k=5))
    longest = [e for e, _ in found.rows if len(e.types) == 5]
    assert [e.types for e in longest] == [("0", "1", "2", "3", "4")]
    truth = spark.createDataFrame([([str(i) for i in range(5)],)], "planted array<string>")
    got = {r["k"]: r["pct_embedded"] for r in measures.recovery(found.frequent(spark).select("types", "freq"), truth, "serial").collect()}
    assert got[1] == pytest.approx(100 * 5 / 16) and all(got[k] == 100 for k in range(2, 6))


def test_recovery_knows_order_and_compounds(spark):
    rows = [(["A", "B"], 9), (["B", "A"], 5), (["A", "C"], 4), (["A", "A"], 7), (["X", "Y"], 3)]
    found = spark.createDataFrame(rows, "types array<string>, freq long")
    truth = spark.createDataFrame([(["A", "B", "C"],), (["Y", "X"],)], "planted array<string>")
    assert [tuple(r) for r in measures.recovery(found, truth, "serial").collect()] == [(2, 40.0, 4)]
    pairs = found.where("types[0] <> types[1]")
    assert [tuple(r) for r in measures.recovery(pairs, truth).collect()] == [(2, 100.0, 3)]
    chains = spark.createDataFrame([(["A", "[B C]"], 6), (["A", "[C D]", "E"], 5), (["[B C]", "A"], 8), (["A", "[B X]"], 2), (["E"], 7)], "types array<string>, freq long")
    truth = spark.createDataFrame([(["A", "[B C D]", "E"],)], "planted array<string>")
    got = {r["k"]: (r["pct_embedded"], r["min_count"]) for r in measures.recovery(chains, truth, "chain").collect()}
    assert got == {1: (100.0, 7), 2: (33.333333, 6), 3: (100.0, 5)}


def test_chunked_choice_equals_the_whole(spark):
    rng = random.Random(5)
    sequences = []
    for _ in range(12):
        t, times = 0, []
        for _ in range(150):
            t += rng.choice([0, 0, 1, 1, 2, 9])
            times.append(t)
        sequences.append(([rng.choice("ABC") for _ in times], times))
    s = frame(spark, *sequences)
    for eps, expiry in (([parallel("AB"), parallel("ABC")], 6), ([serial("ABA", (Gap(0, 4), Gap(0, 9)))], None)):
        whole = sorted(map(str, compound.track(s, eps, expiry).collect()))
        for chunk in (1, 7, 64):
            assert sorted(map(str, compound.track(s, eps, expiry, chunk).collect())) == whole
    plain = serial("AB")
    want = freqs(strategy.count(s, [plain]))
    assert freqs(strategy.count(s, [plain], chunk=5)) == want == freqs(strategy.count(s, [plain], strategy="kernel"))
    assert freqs(strategy.count(s, [parallel("AB")], 6, "auto")) == freqs(strategy.count(s, [parallel("AB")], 6))


def test_null_levels_equal_subsets(spark, monkeypatch):
    null = simulator.null_stream(spark, "fixed", 8, 4, 2, 1)
    rows = lambda: sorted(map(tuple, significance.null_counts(null, "parallel", 4, expiry=20_000).collect()))
    own = rows()
    monkeypatch.setattr(significance, "CROWD", 0)
    assert rows() == own and max(r[1] for r in own) == 4


def test_null_streams_are_flat(spark):
    for model in ("fixed", "shared", "drift", "tied"):
        null = simulator.null_stream(spark, model, 8, 4, 2, 1)
        n = null.count()
        assert 8 * 4 * 2 * 10 * 0.7 < n < 8 * 4 * 2 * 30 * 1.1
        assert null.count() == n
    counts = significance.null_counts(null, "parallel", 3, expiry=1000)
    profile = {r["k"]: r["avg_max"] for r in significance.max_freq_profile(counts, 3, 2).collect()}
    assert profile[1] > 5 * profile[2] > 5 * profile[3]


def test_p_values(spark):
    tops = spark.createDataFrame([(str(d), 2, 10 + d) for d in range(5)], "dataset string, k int, top long")
    found = spark.createDataFrame([("x", 2, 12), ("y", 2, 50), ("z", 3, 1)], "ep_id string, k int, freq long")
    got = {r["ep_id"]: r["p"] for r in significance.p_values(found, tops, 5).collect()}
    assert got == {"x": 0.6, "y": 0.0, "z": 0.0}
    assert significance.threshold_for(tops, 0.05).first()["threshold"] == 14


def test_ids():
    assert Episode("parallel", ("A", "B")).id == "A+B"
    with pytest.raises(ValueError):
        parallel("AA")
    with pytest.raises(ValueError):
        Gap(3, 3)
