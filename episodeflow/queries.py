"""The registered queries: every method, variant, baseline and measure on the given tables, and SQL beside them."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import sqltext as S
from .functions import rates, udfs
from .model import Episode, Gap, parallel, serial
from .operators import automata, baselines, candidates, compound, frequency, measures, occurrences, significance, simulator
from .plans import miner, orders, strategy
from .plans.miner import EpisodePlan
from .sources import streams as T
from .storage import new_path
from .streaming import online

#: Queries go through the distributed plans, however small the tables are.
mine = partial(miner.mine, strategy="windowed")
QUERIES: dict = {}
SQL: dict = {}
HOUR = S.HOUR


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return add


def _gaps(u: int, *pairs: tuple[int, int]) -> list[Gap]:
    return [Gap(lo * u, hi * u, f"({lo},{hi}]") for lo, hi in pairs]


def _sql_gaps(*pairs: tuple[int, int], u: str = S.U) -> list[tuple[str, str, str]]:
    return [(f"({lo},{hi}]", f"{lo} * {u}", f"{hi} * {u}") for lo, hi in pairs]


def _chunk(u: int, span: int | None = None) -> int:
    """A chunk for the one long stream of the events table, whose unit u stands for its rate."""
    n = T.UNIT_TIMES_EVENTS // u
    return frequency.chunk_of(2 * u * n, n, span)


# ---- level one and the stream itself


@query("SELECT CAST(user_id % 26 AS VARCHAR) AS etype, count(*) AS freq, round(count(*) / (SELECT count(*) FROM events), 6) AS rel_freq FROM events GROUP BY 1")
def stream_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.channels(spark, sf_dir)
    n = s.count()
    return s.groupBy("etype").agg(F.count("*").alias("freq"), F.round(F.count("*") / n, 6).alias("rel_freq"))


@query("SELECT event_type AS etype, quantile_cont(d, 0.05) AS q05, quantile_cont(d, 0.5) AS q50, quantile_cont(d, 0.95) AS q95 FROM (SELECT event_type, CAST(epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY event_type, user_id ORDER BY ts, event_id) AS DOUBLE) AS d FROM events) WHERE d IS NOT NULL GROUP BY 1")
def interevent_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.user_events(spark, sf_dir)
    d = F.col("t") - F.lag("t").over(W.partitionBy("stream", "etype").orderBy("t", "eid"))
    rows = s.withColumn("d", d.cast("double")).where("d is not null")
    return rows.groupBy("etype").agg(*[F.percentile("d", q).alias(f"q{int(100 * q):02d}") for q in (0.05, 0.5, 0.95)])


@query("SELECT stream, etype, w, count(*) AS n FROM (SELECT CAST(user_id AS VARCHAR) AS stream, event_type AS etype, epoch_us(ts) // 86400000000 AS w FROM events) GROUP BY ALL")
def rate_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return significance.estimate_rates(T.user_events(spark, sf_dir), 24 * HOUR)


SIX = [("(0,6h]", "0", str(6 * HOUR))]
THREE = [("(0,6h]", "0", str(6 * HOUR)), ("(6h,12h]", str(6 * HOUR), str(12 * HOUR)), ("(12h,24h]", str(12 * HOUR), str(24 * HOUR))]
THREE_GAPS = tuple(Gap(int(lo), int(hi), n) for n, lo, hi in THREE)


# ---- parallel episodes


def _pairs(hours: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return frequency.count(occurrences.parallel_pairs(occurrences.recents(T.user_events(spark, sf_dir), hours * HOUR)))

    return run


for _h in (2, 6, 24):
    query(S.counted(S.USER, S.PAIRS, S.near(_h * HOUR)), f"parallel_pairs_{_h}h")(_pairs(_h))


@query(S.counted(S.USER, S.TRIPLES, S.near(24 * HOUR)))
def parallel_triples_24h(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.user_events(spark, sf_dir)
    types = sorted(r[0] for r in s.select("etype").distinct().collect())
    return strategy.count(s, candidates.next_parallel([parallel(p) for p in __import__("itertools").combinations(types, 2)]), 24 * HOUR)


@query(f"WITH a AS ({S.counted(S.CHANNEL, S.PAIRS, S.near(S.U), 'SELECT ep_id, 2 AS k, freq FROM freq')}), b AS ({S.counted(S.CHANNEL, S.TRIPLES, S.near(S.U), 'SELECT ep_id, 3 AS k, freq FROM freq')}), c AS (SELECT CAST(user_id % 26 AS VARCHAR) AS ep_id, 1 AS k, count(*) AS freq FROM events GROUP BY 1) SELECT * FROM a WHERE freq >= 8 UNION ALL SELECT * FROM b WHERE freq >= 8 UNION ALL SELECT * FROM c WHERE freq >= 8")
def parallel_levels_channels(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = T.unit(spark, sf_dir)
    return mine(T.channels(spark, sf_dir), EpisodePlan("parallel", 8, expiry=u)).frequent(spark).select("ep_id", "k", "freq")


@query(SQL["parallel_levels_channels"])
def recording_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same levels by the way that `auto` takes for recordings one task can hold; beyond that size it takes the other."""
    u = T.unit(spark, sf_dir)
    return miner.mine(T.channels(spark, sf_dir), EpisodePlan("parallel", 8, expiry=u)).frequent(spark).select("ep_id", "k", "freq")


@query(S.counted(S.USER, S.serial2(THREE), select="SELECT ep_id, freq FROM freq WHERE freq >= 300"))
def recording_serial_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return miner.mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 300, gaps=THREE_GAPS, max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query(" UNION ALL ".join(f"SELECT '{m}' AS expiry, count(*) FILTER (freq >= 8) AS n_frequent, max(freq) AS max_freq, CAST(sum(freq) AS BIGINT) AS total FROM ({S.counted(S.CHANNEL, S.PAIRS, S.near(x))})" for m, x in (("0.1", f"{S.U} // 10"), ("1", S.U), ("2", f"2 * {S.U}"), ("7", f"7 * {S.U}"))))
def parallel_expiry_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    u, s, out = T.unit(spark, sf_dir), T.channels(spark, sf_dir), None
    for m, x in (("0.1", u // 10), ("1", u), ("2", 2 * u), ("7", 7 * u)):
        c = frequency.count(occurrences.parallel_pairs(occurrences.recents(s, x)), _chunk(u, x))
        part = c.agg(F.lit(m).alias("expiry"), F.count(F.when(F.col("freq") >= 8, 1)).alias("n_frequent"), F.max("freq").alias("max_freq"), F.sum("freq").alias("total"))
        out = part if out is None else out.unionByName(part)
    return out


@query("WITH s AS (SELECT vec_id, lpad(CAST(i - 1 AS VARCHAR), 2, '0') AS etype FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE x > 0.2) SELECT a.etype || '+' || b.etype AS ep_id, count(*) AS freq FROM s AS a JOIN s AS b ON a.vec_id = b.vec_id AND a.etype < b.etype GROUP BY 1")
def parallel_same_tick_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frequency.count(occurrences.parallel_pairs(occurrences.same_tick(T.co_firing(spark, sf_dir, 0.2))))


# ---- serial episodes

@query(S.counted(S.USER, S.serial2(SIX)))
def serial_pairs_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frequency.count(occurrences.serial_pairs(T.user_events(spark, sf_dir), Gap(0, 6 * HOUR, "(0,6h]")))


SWEEP = ((0, 1), (0, 2), (2, 4), (4, 6))


@query(" UNION ALL ".join(f"SELECT '({lo},{hi}]' AS gap, count(*) FILTER (freq >= 8) AS n_frequent, max(freq) AS max_freq, CAST(sum(freq) AS BIGINT) AS total FROM ({S.counted(S.CHANNEL, S.serial2(_sql_gaps((lo, hi))))})" for lo, hi in SWEEP))
def serial_interval_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    u, s, out = T.unit(spark, sf_dir), T.channels(spark, sf_dir), None
    for g in (Gap(lo * u, hi * u, f"({lo},{hi}]") for lo, hi in SWEEP):
        c = frequency.count(occurrences.serial_pairs(s, g), _chunk(u, g.hi))
        part = c.agg(F.lit(g.label).alias("gap"), F.count(F.when(F.col("freq") >= 8, 1)).alias("n_frequent"), F.max("freq").alias("max_freq"), F.sum("freq").alias("total"))
        out = part if out is None else out.unionByName(part)
    return out


@query(S.counted(S.USER, S.serial2(THREE), select="SELECT ep_id, freq FROM freq WHERE freq >= 300"))
def serial_generalised_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 300, gaps=THREE_GAPS, max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query(S.counted(S.USER, S.grow("p2", THREE), f"p2 AS MATERIALIZED ({S.serial2(THREE)})", "SELECT ep_id, freq FROM freq WHERE freq >= 60"))
def serial_generalised_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 60, gaps=THREE_GAPS, max_k=3)).frequent(spark).where("k = 3").select("ep_id", "freq")


@query(S.counted(S.USER, S.serial2(THREE), select="SELECT types, best_ep AS ep_id, freq FROM (SELECT split_part(ep_id, '-', 1) || '>' || split_part(ep_id, '->', 2) AS types, ep_id AS best_ep, freq, row_number() OVER (PARTITION BY split_part(ep_id, '-', 1), split_part(ep_id, '->', 2) ORDER BY freq DESC, ep_id) AS r FROM freq) WHERE r = 1"))
def serial_best_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 0, gaps=THREE_GAPS, max_k=2)).frequent(spark).where("k = 2")
    return miner.best_intervals(found).select(F.array_join("types", ">").alias("types"), "ep_id", "freq")


_LATEST = "SELECT f.stream, n.etype || '->' || f.etype AS ep_id, max(n.p) AS s, f.p AS e FROM s AS f JOIN s AS n ON n.stream = f.stream AND n.t < f.t{} GROUP BY f.stream, n.etype, f.etype, f.p"


@query(S.counted(S.USER, _LATEST.format(f" AND f.t - n.t <= {6 * HOUR}")))
def serial_span_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 0, expiry=6 * HOUR, max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query(S.counted(S.USER, _LATEST.format("")))
def serial_plain_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 0, max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query(S.counted(S.USER, S.grow("p2", SIX), f"p2 AS MATERIALIZED ({S.serial2(SIX)})", "SELECT 'within' AS verdict, count(*) AS n FROM freq AS f JOIN f2 AS a ON starts_with(f.ep_id, a.ep_id || '-') JOIN f2 AS b ON ends_with(f.ep_id, '->' || b.ep_id) WHERE f.freq <= least(a.freq, b.freq)", f"f2 AS ({S.counted(S.USER, S.serial2(SIX))})"))
def serial_prefix_suffix_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many three-node episodes are no more frequent than their prefix and their suffix: all of them."""
    found = mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 0, gaps=(Gap(0, 6 * HOUR, "(0,6h]"),), max_k=3)).frequent(spark)
    two = found.where("k = 2").select("types", "freq")
    three = found.where("k = 3").select("types", F.col("freq").alias("f"), F.slice("types", 1, 2).alias("p"), F.slice("types", 2, 2).alias("q"))
    both = three.join(two.toDF("p", "fp"), "p").join(two.toDF("q", "fq"), "q").where("f <= least(fp, fq)")
    return both.agg(F.lit("within").alias("verdict"), F.count("*").alias("n"))


# ---- candidates


@query(S.counted(S.USER, S.PAIRS, S.near(24 * HOUR), "SELECT array_to_string(list_sort([a.x, a.y, b.y]), '+') AS ep_id FROM p AS a JOIN p AS b ON a.x = b.x AND a.y < b.y JOIN p AS c ON c.x = a.y AND c.y = b.y", "p AS (SELECT split_part(ep_id, '+', 1) AS x, split_part(ep_id, '+', 2) AS y FROM freq WHERE freq >= (SELECT median(freq) FROM freq))"))
def candidates_parallel(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = frequency.count(occurrences.parallel_pairs(occurrences.recents(T.user_events(spark, sf_dir), 24 * HOUR)))
    mid = c.agg(F.percentile("freq", 0.5).alias("m"))
    kept = c.crossJoin(F.broadcast(mid)).where("freq >= m").select(F.split("ep_id", r"\+").alias("types"))
    return candidates.parallel_candidates(kept).select(F.array_join("types", "+").alias("ep_id"))


@query(S.counted(S.USER, S.serial2(THREE), select="SELECT a.ep_id || substr(b.ep_id, length(b.x) + 1) AS ep_id FROM p AS a JOIN p AS b ON a.y = b.x", more="p AS (SELECT ep_id, split_part(ep_id, '-', 1) AS x, split_part(ep_id, '->', 2) AS y FROM freq WHERE freq >= 300)"))
def candidates_serial(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 300, gaps=THREE_GAPS, max_k=2)).frequent(spark).where("k = 2")
    c = candidates.serial_candidates(found.select("types", "gaps"))
    return c.select(F.concat(F.col("types")[0], F.lit("-"), F.col("gaps")[0], F.lit("->"), F.col("types")[1], F.lit("-"), F.col("gaps")[1], F.lit("->"), F.col("types")[2]).alias("ep_id"))


# ---- occurrences, groups and chains on the planted overlay

GROUP = "0+1+2"
_GROUP_SQL = f"SELECT * FROM ({S.TRIPLES}) WHERE ep_id = '{GROUP}'"


def _overlay(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    u = T.unit(spark, sf_dir)
    return T.overlay(spark, sf_dir, u), u


@query(S.counted(S.OVERLAY, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U), "SELECT ep_id, freq FROM h AS x WHERE NOT EXISTS (SELECT 1 FROM h AS y WHERE len(y.t) = len(x.t) + 1 AND list_has_all(y.t, x.t)) AND len(x.t) > 1", "h AS (SELECT ep_id, freq, string_split(ep_id, '+') AS t FROM freq WHERE freq >= (SELECT count(*) FROM events) // 100)"))
def maximal_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    found = mine(s, EpisodePlan("parallel", n // 100, expiry=u)).frequent(spark)
    return measures.maximal(found).where("k > 1").select("ep_id", "freq")


_CHOSEN = "SELECT g.e, max(iv.s) AS s FROM g JOIN iv ON g.e = iv.e AND g.ep_id = iv.ep_id GROUP BY g.e"


@query(S.counted(S.OVERLAY, _GROUP_SQL, S.near(S.U), f"SELECT row_number() OVER (ORDER BY e) AS occ_no, CAST(s // 1000000000000 AS BIGINT) AS s_t, CAST(e // 1000000000000 AS BIGINT) AS e_t FROM ({_CHOSEN})"))
def occurrences_tracked(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    return compound.track(s, [parallel(GROUP.split("+"))], u, _chunk(u, u)).select("occ_no", F.col("s.t").alias("s_t"), F.col("e.t").alias("e_t"))


_MEMBERS = f"m AS MATERIALIZED (SELECT c.e, near.a, max(near.s) AS p FROM ({_CHOSEN}) AS c JOIN near ON near.e = c.e WHERE near.a IN ('0', '1', '2') GROUP BY c.e, near.a)"


@query(S.counted(S.OVERLAY, _GROUP_SQL, S.near(S.U), "SELECT dense_rank() OVER (ORDER BY e) AS occ_no, a AS etype, CAST(p // 1000000000000 AS BIGINT) AS t FROM m", _MEMBERS))
def occurrence_raster(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    return compound.raster(compound.track(s, [parallel(GROUP.split("+"))], u, _chunk(u, u)), 0, 1 << 60).select("occ_no", "etype", "t")


def _rewrite(anchor: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s, u = _overlay(spark, sf_dir)
        new = compound.rewrite(s, compound.track(s, [parallel(GROUP.split("+"))], u, _chunk(u, u)), anchor)
        return new.groupBy("etype").agg(F.count("*").alias("n"), F.sum(F.col("t") - 1_700_000_000_000_000).alias("sum_t"), F.sum("eid").alias("sum_eid"))

    return run


_COMPOUND = "c AS (SELECT {} AS t, min(CAST(p % 1000000000000 AS BIGINT)) AS eid FROM m GROUP BY e)"
_REWRITTEN = ("w AS MATERIALIZED (SELECT stream, etype, t, eid FROM s WHERE eid NOT IN (SELECT CAST(p % 1000000000000 AS BIGINT) FROM m) UNION ALL SELECT 'all', '[0 1 2]', t, eid FROM c)")
_ANCHORS = {"midpoint": "CAST((min(p // 1000000000000) + max(p // 1000000000000)) // 2 AS BIGINT)", "mean": "CAST(sum(p // 1000000000000) // 3 AS BIGINT)"}
for _a, _x in _ANCHORS.items():
    query(S.counted(S.OVERLAY, _GROUP_SQL, S.near(S.U), "SELECT etype, count(*) AS n, CAST(sum(t - 1700000000000000) AS BIGINT) AS sum_t, CAST(sum(eid) AS BIGINT) AS sum_eid FROM w GROUP BY etype", f"{_MEMBERS}, {_COMPOUND.format(_x)}, {_REWRITTEN}"), f"chain_rewrite_{_a}")(_rewrite(_a))

FIVE = ((0, 2), (2, 4), (4, 6), (6, 8), (8, 10))


@query()
def chain_mine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups at one unit, rewritten, and chains over five candidate intervals."""
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    _, _, chains = compound.mine_chain(s, EpisodePlan("parallel", n // 100, expiry=u), EpisodePlan("serial", n // 100, gaps=tuple(_gaps(u, *FIVE))), strategy="windowed")
    return chains.frequent(spark).select("ep_id", "k", "freq", "maximal")


@query(S.counted(S.OVERLAY, _GROUP_SQL, S.near(S.U), "SELECT ep_id, freq FROM f2 WHERE freq >= (SELECT count(*) FROM events) // 100", f"{_MEMBERS}, {_COMPOUND.format(_ANCHORS['midpoint'])}, {_REWRITTEN}, f2 AS ({S.counted('SELECT * FROM w', S.serial2(_sql_gaps(*FIVE)))})"))
def chain_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    new = compound.rewrite(s, compound.track(s, [parallel(GROUP.split("+"))], u, _chunk(u, u)))
    return mine(new, EpisodePlan("serial", n // 100, gaps=tuple(_gaps(u, *FIVE)), max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query(S.counted(S.OVERLAY, _GROUP_SQL, S.near(S.U), "SELECT ep_id, freq FROM f3 WHERE freq >= (SELECT count(*) FROM events) // 100", f"{_MEMBERS}, {_COMPOUND.format(_ANCHORS['midpoint'])}, {_REWRITTEN}, f3 AS ({S.counted('SELECT * FROM w', S.grow('p2', _sql_gaps(*FIVE)), f'p2 AS MATERIALIZED ({S.serial2(_sql_gaps(*FIVE))})')})"))
def chain_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains of three nodes over five candidate intervals, the group rewritten: the whole way from the stream."""
    return chain_mine(spark, sf_dir).where("k = 3").select("ep_id", "freq")


_LINE = "['23', '0', '1', '2', '3', '4', '5']"


@query(S.counted(S.OVERLAY, S.serial2(_sql_gaps((0, 2), (2, 4))), select=f"SELECT 2 AS k, round(100.0 * count(*) FILTER (i) / count(*), 6) AS pct_embedded, min(freq) FILTER (i) AS min_count FROM (SELECT freq, list_position({_LINE}, split_part(ep_id, '-', 1)) < list_position({_LINE}, split_part(ep_id, '->', 2)) AND true AS i FROM freq WHERE freq >= (SELECT count(*) FROM events) // 200)".replace("AND true", "IS TRUE")))
def overlay_recovery_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ordered pairs against the planted order: a pair the other way round isn't part of it."""
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    found = mine(s, EpisodePlan("serial", n // 200, gaps=tuple(_gaps(u, (0, 2), (2, 4))), max_k=2)).frequent(spark).where("k = 2")
    truth = spark.createDataFrame([([str(c) for _, c, _ in T.PLANTED],)], "planted array<string>")
    every = measures.recovery(found.select(F.concat("types", "gaps").alias("id"), "types", "freq").select("types", "freq"), truth, "serial")
    return every.select("k", "pct_embedded", "min_count")


@query(S.counted(S.OVERLAY, S.grow("p2", _sql_gaps((2, 4), (4, 6))), f"p2 AS MATERIALIZED ({S.serial2(_sql_gaps((2, 4), (4, 6)))})", "SELECT count(*) AS sound, count(*) FILTER (EXISTS (SELECT 1 FROM h WHERE h.a = x AND h.b = y) AND EXISTS (SELECT 1 FROM h WHERE h.a = y AND h.b = z) AND EXISTS (SELECT 1 FROM h WHERE h.a = x AND h.b = z)) AS unsound FROM (SELECT split_part(ep_id, '-', 1) AS x, split_part(split_part(ep_id, '->', 2), '-', 1) AS y, split_part(ep_id, '->', 3) AS z FROM freq WHERE freq >= (SELECT count(*) FROM events) // 100)", f"h AS (SELECT split_part(ep_id, '-', 1) AS a, split_part(ep_id, '->', 2) AS b FROM ({S.counted(S.OVERLAY, S.serial2(_sql_gaps((2, 4), (4, 6))))}) WHERE freq >= (SELECT count(*) FROM events) // 100)"))
def pruning_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frequent orders of three with the pruning that is sound for gaps, and with that by all subsets, which loses some."""
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    counts = []
    for prune in ("ends", "all"):
        found = mine(s, EpisodePlan("serial", n // 100, gaps=tuple(_gaps(u, (2, 4), (4, 6))), max_k=3, prune=prune))
        counts.append(sum(len(e.types) == 3 for e, _ in found.rows))
    return spark.createDataFrame([tuple(counts)], "sound long, unsound long")


@query(S.counted(S.OVERLAY, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U), "SELECT len(t) AS k, round(100.0 * count(*) FILTER (list_has_all(['23', '0', '1', '2', '3', '4', '5'], t)) / count(*), 6) AS pct_embedded, min(freq) FILTER (list_has_all(['23', '0', '1', '2', '3', '4', '5'], t)) AS min_count FROM h GROUP BY 1", "h AS (SELECT freq, string_split(ep_id, '+') AS t FROM freq WHERE freq >= (SELECT count(*) FROM events) // 100 UNION ALL SELECT count(*), [etype] FROM s GROUP BY etype HAVING count(*) >= (SELECT count(*) FROM events) // 100)"))
def overlay_recovery(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    found = mine(s, EpisodePlan("parallel", n // 100, expiry=u)).frequent(spark)
    truth = spark.createDataFrame([([str(c) for _, c, _ in T.PLANTED],)], "planted array<string>")
    return measures.recovery(found.select("types", "freq"), truth)


@query(S.counted(S.OVERLAY, S.serial2(_sql_gaps(*FIVE)), select="SELECT ep_id, freq FROM freq WHERE freq >= (SELECT count(*) FROM events) // 50"))
def overlay_interval_discovery(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    return mine(s, EpisodePlan("serial", n // 50, gaps=tuple(_gaps(u, *FIVE)), max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query(" UNION ALL ".join(f"SELECT {m} AS expiry, count(*) FILTER (freq >= 100) AS n_frequent, max(freq) FILTER (ep_id = '0+1+2') AS planted FROM ({S.counted(S.OVERLAY, f'{S.PAIRS} UNION ALL {_GROUP_SQL}', S.near(f'{m} * {S.U}'))})" for m in (1, 2, 4, 6)))
def overlay_expiry_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    (s, u), out = _overlay(spark, sf_dir), None
    for m in (1, 2, 4, 6):
        near = miner._cut(occurrences.recents(s, m * u))
        c = frequency.count(occurrences.parallel_pairs(near).unionByName(occurrences.parallel_intervals(near, [parallel(GROUP.split("+"))])), _chunk(u, m * u))
        part = c.agg(F.lit(m).alias("expiry"), F.count(F.when(F.col("freq") >= 100, 1)).alias("n_frequent"), F.max(F.when(F.col("ep_id") == GROUP, F.col("freq"))).alias("planted"))
        out = part if out is None else out.unionByName(part)
    return out


@query(S.counted(S.OVERLAY, S.serial2(_sql_gaps((0, 2), (2, 4), (4, 6), (6, 8))), select="SELECT split_part(split_part(ep_id, '->', 1), '-', 2) AS gap, count(*) FILTER (freq >= 100) AS n_frequent, max(freq) AS max_freq FROM freq GROUP BY 1"))
def overlay_interval_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    (s, u), out = _overlay(spark, sf_dir), None
    for g in _gaps(u, (0, 2), (2, 4), (4, 6), (6, 8)):
        c = frequency.count(occurrences.serial_pairs(s, g), _chunk(u, g.hi))
        part = c.agg(F.lit(g.label).alias("gap"), F.count(F.when(F.col("freq") >= 100, 1)).alias("n_frequent"), F.max("freq").alias("max_freq"))
        out = part if out is None else out.unionByName(part)
    return out


@query(S.counted(S.OVERLAY, S.serial2(_sql_gaps((4, 6))), select="SELECT split_part(ep_id, '-', 1) AS src, split_part(ep_id, '->', 2) AS dst, '(4,6]' AS gap, freq FROM freq WHERE freq >= (SELECT count(*) FROM events) // 100"))
def connectivity_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    n = T.load(spark, sf_dir, "events").count()
    return measures.connectivity(mine(s, EpisodePlan("serial", n // 100, gaps=tuple(_gaps(u, (4, 6))), max_k=2)).frequent(spark))


# ---- nulls, profiles and significance

SETS = 5
_JITTER = f"SELECT 'all/' || d AS stream, CAST(user_id % 26 AS VARCHAR) AS etype, epoch_us(ts) + ((event_id % 2147483648 * 1103515245 + 12345 + d * 2654435761 + 40503) % 2147483648 * 69069 + 1) % 2147483648 % (40 * {S.U} - 1) - (20 * {S.U} - 1) AS t, event_id AS eid FROM events, range({SETS}) AS r(d)"
_TOPS = "tops AS (SELECT split_part(stream, '/', 2) AS d, len(string_split(ep_id, '+')) AS k, ep_id, count(*) AS f FROM g GROUP BY ALL UNION ALL SELECT split_part(stream, '/', 2), 1, etype, count(*) FROM s GROUP BY ALL), t AS (SELECT d, k, max(f) AS top FROM tops GROUP BY ALL)"
_NULL_SQL = (_JITTER, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U))


def _null_tops(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = T.unit(spark, sf_dir)
    null = significance.jitter(T.channels(spark, sf_dir), 20 * u, SETS)
    return significance.null_counts(null, "parallel", 3, expiry=u, chunk=_chunk(u, u))


@query(S.counted(*_NULL_SQL, f"SELECT CAST(x.k AS INTEGER) AS k, round(coalesce(sum(top), 0) / {SETS}, 6) AS avg_max, coalesce(max(top), 0) AS max_max, CASE WHEN count(top) = {SETS} THEN min(top) ELSE 0 END AS min_max FROM range(1, 4) AS x(k) LEFT JOIN t USING (k) GROUP BY x.k", _TOPS))
def jitter_null_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return significance.max_freq_profile(_null_tops(spark, sf_dir), 3, SETS)


@query(S.counted(*_NULL_SQL, "SELECT o.ep_id, o.k, o.freq, round((SELECT count(*) FROM t WHERE t.k = o.k AND t.top >= o.freq) / 5, 6) AS p FROM o", f"{_TOPS}, o AS (SELECT ep_id, 2 AS k, freq FROM ({S.counted(S.OVERLAY, S.PAIRS, S.near(S.U))}) WHERE freq >= 20)"))
def null_p_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    found = mine(s, EpisodePlan("parallel", 20, expiry=u, max_k=2)).frequent(spark).where("k = 2").select("ep_id", "k", "freq")
    tops = _null_tops(spark, sf_dir).groupBy("dataset", "k").agg(F.max("freq").alias("top"))
    return significance.p_values(found, tops, SETS)


@query(S.counted(*_NULL_SQL, "SELECT CAST(k AS INTEGER) AS k, CAST(floor(quantile_cont(top, 0.95)) + 1 AS BIGINT) AS threshold FROM t GROUP BY k", _TOPS))
def null_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    tops = _null_tops(spark, sf_dir).groupBy("dataset", "k").agg(F.max("freq").alias("top"))
    return significance.threshold_for(tops, 0.05)


@query(S.counted(_JITTER, S.serial2(_sql_gaps((4, 6))), select=f"SELECT 2 AS k, round(sum(top) / {SETS}, 6) AS avg_max, max(top) AS max_max, min(top) AS min_max FROM (SELECT stream, max(f) AS top FROM (SELECT stream, ep_id, count(*) AS f FROM g GROUP BY ALL) GROUP BY stream)"))
def serial_null_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = T.unit(spark, sf_dir)
    null = significance.jitter(T.channels(spark, sf_dir), 20 * u, SETS)
    counts = significance.null_counts(null, "serial", 2, gaps=tuple(_gaps(u, (4, 6))), chunk=_chunk(u, 6 * u))
    return significance.max_freq_profile(counts, 2, SETS).where("k = 2")


@query(S.counted(_JITTER, S.serial2(_sql_gaps((2, 4), (4, 6), (6, 8))), select=f"SELECT 2 AS k, round(sum(top) / {SETS}, 6) AS avg_max, max(top) AS max_max, min(top) AS min_max FROM (SELECT stream, max(f) AS top FROM (SELECT stream, ep_id, count(*) AS f FROM g GROUP BY ALL) GROUP BY stream)"))
def discovery_null_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = T.unit(spark, sf_dir)
    null = significance.jitter(T.channels(spark, sf_dir), 20 * u, SETS)
    counts = significance.null_counts(null, "serial", 2, gaps=tuple(_gaps(u, (2, 4), (4, 6), (6, 8))), chunk=_chunk(u, 8 * u))
    return significance.max_freq_profile(counts, 2, SETS).where("k = 2")


_PLANTED_SETS = " UNION ALL ".join(f"SELECT '{i}' AS d, freq FROM ({S.counted(S.overlay(i), _GROUP_SQL, S.near(S.U))})" for i in range(4))


@query(f"SELECT 3 AS k, round(avg(freq), 6) AS avg_min, max(freq) AS max_min, min(freq) AS min_min FROM ({_PLANTED_SETS})")
def planted_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The planted group over four overlays of different drop-out."""
    u, parts = T.unit(spark, sf_dir), []
    for i in range(4):
        parts.append(T.overlay(spark, sf_dir, u, i).withColumn("stream", F.lit(str(i))))
    s = T.merge_streams(*parts)
    c = frequency.count_by_stream(occurrences.parallel_intervals(occurrences.recents(s, u), [parallel(GROUP.split("+"))]))
    return significance.min_freq_profile(c.select(F.col("stream").alias("dataset"), F.lit(3).alias("k"), "ep_id", "freq"))


@query(S.counted(S.OVERLAY, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U), f"SELECT CAST(a.k AS INTEGER) AS k, b.top AS noise, a.low AS planted FROM (SELECT len(string_split(ep_id, '+')) AS k, min(freq) AS low FROM freq WHERE ep_id IN ('0+1', '0+2', '1+2', '0+1+2') GROUP BY 1) AS a FULL JOIN (SELECT k, max(top) AS top FROM n GROUP BY k) AS b USING (k)", f"n AS (SELECT * FROM ({S.counted(*_NULL_SQL, 'SELECT k, top FROM t WHERE k > 1', _TOPS)}))"))
def noise_vs_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    near = miner._cut(occurrences.recents(s, u))
    c = frequency.count(occurrences.parallel_intervals(near, [parallel(x.split("+")) for x in ("0+1", "0+2", "1+2", GROUP)]), _chunk(u, u))
    low = c.groupBy(F.size(F.split("ep_id", r"\+")).alias("k")).agg(F.min("freq").alias("planted"))
    top = _null_tops(spark, sf_dir).where("k > 1").groupBy("k").agg(F.max("freq").alias("noise"))
    return low.join(top, "k", "full_outer").select("k", "noise", "planted")


_WINDOW = f"(500 * {S.U})"
_DRAWN = " + ".join(f"((event_id % 2147483648 * {f} + 12345 + d * 2654435761 + 3 * 40503) % 2147483648 * 69069 + 1) % 2147483648{m}" for f, m in ((1103515245, " * 2147483648"), (22695477, "")))
_CALIBRATED = f"SELECT 'all/' || d AS stream, CAST(user_id % 26 AS VARCHAR) AS etype, epoch_us(ts) // {_WINDOW} * {_WINDOW} + ({_DRAWN}) % {_WINDOW} AS t, event_id AS eid FROM events, range({SETS}) AS r(d)"
_PROFILE = f"SELECT CAST(x.k AS INTEGER) AS k, round(coalesce(sum(top), 0) / {SETS}, 6) AS avg_max, coalesce(max(top), 0) AS max_max, CASE WHEN count(top) = {SETS} THEN min(top) ELSE 0 END AS min_max FROM range(1, {{}}) AS x(k) LEFT JOIN t USING (k) GROUP BY x.k"


@query(S.counted(_CALIBRATED, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U), _PROFILE.format(4), _TOPS))
def calibrated_null(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Surrogates with the data's own windowed rates: profile of their highest frequencies."""
    u = T.unit(spark, sf_dir)
    null = significance.calibrated_null(T.channels(spark, sf_dir), 500 * u, SETS, 3)
    return significance.max_freq_profile(significance.null_counts(null, "parallel", 3, expiry=u, chunk=_chunk(u, u)), 3, SETS)


_RATES = f"SELECT CAST(user_id % 26 AS VARCHAR) AS unit, count(*) * 1000.0 * {S.U} / (SELECT max(epoch_us(ts)) - min(epoch_us(ts)) FROM events) AS lam FROM events GROUP BY 1"
_SHIFT = "ln(-ln(0.05) / 0.001 / lam - 1)"


@query(f"SELECT unit, round(lam, 6) AS lam, round(-ln(0.05) / 0.001, 6) AS lam_max, round({_SHIFT}, 6) AS displacement, round({_SHIFT} + ln(9), 6) AS strong_weight, round(1.5 * lam * 0.05, 6) AS compensated FROM (SELECT unit, CAST(lam AS DOUBLE) AS lam FROM ({_RATES}))")
def rate_parameters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The constants of each channel as a unit of the simulator, from its rate in the events (a unit of time for a millisecond)."""
    own = significance.mean_rates(T.channels(spark, sf_dir), T.unit(spark, sf_dir))
    p = rates.parameters(spark, own=own.select(F.col("etype").alias("unit"), "lam"))
    return p.select("unit", F.round("lam", 6).alias("lam"), "lam_max", "displacement", "strong_weight", "compensated")


def _unit_rates(spark: SparkSession, sf_dir: str, n: int) -> dict[int, float]:
    """Spikes a second of n units: the rates of as many channels of the events, their mean near the usual 20. Units without
    an event keep the usual rate; none fires faster than half of what a step allows."""
    own = significance.mean_rates(T.channels(spark, sf_dir, n), T.unit(spark, sf_dir) * n // 26).collect()
    most = simulator.Network(n).lam_max / 2
    return {int(r["etype"]): min(r["lam"], most) for r in own if r["etype"] is not None and int(r["etype"]) >= 0}


def _planted_run(spark: SparkSession, net, plan: EpisodePlan, seconds: float) -> DataFrame:
    """Sizes, shares inside a planted pattern and least counts, of the pattern's own kind."""
    s = miner._cut(simulator.simulate(spark, net, seconds, 1, 5))
    found = miner.mine(s, plan).frequent(spark)
    truth = spark.createDataFrame([([str(i) for layer in layers for i in layer],) for layers in net.truth], "planted array<string>")
    return measures.recovery(found.select("types", "freq"), truth, plan.kind)


def _blocks(patterns: int, size: int) -> list[list[int]]:
    return [list(range(k * size, (k + 1) * size)) for k in range(patterns)]


@query()
def simulate_synchrony(spark: SparkSession, sf_dir: str) -> DataFrame:
    """64 channels, 50 s, two groups of 8 that a unit of their own fires: how much of what is found was planted."""
    net = simulator.Network(64, simulator.random_network(64, 2, 0.5, 1), _unit_rates(spark, sf_dir, 64))
    for k, b in enumerate(_blocks(2, 8)):
        simulator.plant(net, [[16 + k], b])
    net.truth = [layers[1:] for layers in net.truth]
    return _planted_run(spark, net, EpisodePlan("parallel", 300, expiry=1000), 50)


@query()
def simulate_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    net = simulator.Network(64, simulator.random_network(64, 2, 0.5, 2), _unit_rates(spark, sf_dir, 64))
    for b in _blocks(2, 8):
        simulator.plant(net, [[i] for i in b])
    return _planted_run(spark, net, EpisodePlan("serial", 300, gaps=(Gap(4000, 6000),)), 50)


@query()
def simulate_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A chain of four groups of four behind single units: groups, rewriting, chain."""
    net = simulator.Network(64, simulator.random_network(64, 2, 0.5, 3), _unit_rates(spark, sf_dir, 64))
    layers = [x for k in range(4) for x in ([k], list(range(8 + 4 * k, 12 + 4 * k)))]
    simulator.plant(net, layers)
    s = miner._cut(simulator.simulate(spark, net, 50, 1, 6))
    _, _, chains = compound.mine_chain(s, EpisodePlan("parallel", 300, expiry=1000), EpisodePlan("serial", 100, gaps=(Gap(4000, 6000),), max_k=8), mode="types")
    return chains.frequent(spark).where("k > 1").select("ep_id", "k", "freq", "maximal")


@query()
def simulate_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Profiles of the highest frequency on null streams of four rate models and of random networks, at the rates of the events."""
    out, own = None, _unit_rates(spark, sf_dir, 26)
    low, high = min(own.values(), default=10.0), max(own.values(), default=30.0)
    for model in ("fixed", "shared", "drift", "tied", "network"):
        null = simulator.null_networks(spark, 26, 0.5, 10, 2, 9, own) if model == "network" else simulator.null_stream(spark, model, 26, 10, 2, 9, low, high)
        null = miner._cut(null)
        part = significance.max_freq_profile(significance.null_counts(null, "parallel", 4, expiry=1000), 4, 2).withColumn("model", F.lit(model))
        out = part if out is None else out.unionByName(part)
    return out


# ---- confidence, trend, similarity

_DAYS = "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) || '/' || user_id AS stream, event_type AS etype, epoch_us(ts) AS t, event_id AS eid FROM events"


def _daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.as_stream(T.load(spark, sf_dir, "events"), T.EventStreamSpec("concat(cast(cast(ts as date) as string), '/', user_id)", "event_type", "ts", "event_id"))


def _day_pairs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    s = _daily(spark, sf_dir)
    c = frequency.count_by_stream(occurrences.serial_pairs(s, Gap(0, 6 * HOUR, "(0,6h]")))
    day = F.substring_index("stream", "/", 1)
    return s, c.groupBy(day.alias("day"), "ep_id").agg(F.sum("freq").alias("freq"))


@query(S.counted(_DAYS, S.serial2(SIX), select="SELECT d.day, split_part(d.ep_id, '-', 1) AS a, split_part(d.ep_id, '->', 2) AS b, d.freq, round(d.freq / n.n, 6) AS conf FROM d JOIN (SELECT split_part(stream, '/', 1) AS day, etype, count(*) AS n FROM s GROUP BY ALL) AS n ON n.day = d.day AND n.etype = split_part(d.ep_id, '-', 1)", more="d AS (SELECT split_part(stream, '/', 1) AS day, ep_id, count(*) AS freq FROM g GROUP BY ALL)"))
def pair_confidence_by_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, c = _day_pairs(spark, sf_dir)
    ends = c.select("day", F.split("ep_id", "-")[0].alias("a"), F.split("ep_id", "->")[1].alias("b"), "freq")
    ones = s.groupBy(F.substring_index("stream", "/", 1).alias("day"), "etype").agg(F.count("*").alias("n"))
    return measures.pair_confidence(ends, ones, ("day",))


@query(S.counted(_DAYS, S.serial2(SIX), select="SELECT ep_id, count(*) AS days, round(regr_slope(rel, day), 9) AS slope, round(arg_max(step, day) , 9) AS last_step FROM (SELECT *, rel - lag(rel) OVER (PARTITION BY ep_id ORDER BY day) AS step FROM (SELECT d.ep_id, datediff('day', DATE '1970-01-01', CAST(d.day AS DATE)) AS day, d.freq / n.n AS rel FROM d JOIN (SELECT split_part(stream, '/', 1) AS day, count(*) AS n FROM s GROUP BY ALL) AS n ON n.day = d.day)) GROUP BY ep_id", more="d AS (SELECT split_part(stream, '/', 1) AS day, ep_id, count(*) AS freq FROM g GROUP BY ALL)"))
def frequency_trend(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, c = _day_pairs(spark, sf_dir)
    n = s.groupBy(F.substring_index("stream", "/", 1).alias("day")).agg(F.count("*").alias("n"))
    rows = c.join(n, "day").withColumn("day", F.datediff(F.col("day").cast("date"), F.lit("1970-01-01").cast("date")))
    return measures.frequency_trend(rows)


_SLICES = "SELECT (user_id % 6) || '-' || CAST(ts AS DATE) AS stream, event_type AS etype, epoch_us(ts) AS t, event_id AS eid FROM events WHERE CAST(ts AS DATE) > (SELECT max(CAST(ts AS DATE)) - 5 FROM events) AND NOT (user_id % 6 = 5 AND CAST(ts AS DATE) = (SELECT max(CAST(ts AS DATE)) FROM events))"
DAYGAP = [("(0,24h]", "0", str(24 * HOUR))]
TOP, SLICE_TYPES = 20, 24
_TOP_SQL = "r AS (SELECT stream AS slice, ep_id, count(*) AS freq FROM g GROUP BY ALL), q AS MATERIALIZED (SELECT slice, ep_id, freq, rank FROM (SELECT *, row_number() OVER (PARTITION BY slice ORDER BY freq DESC, ep_id) AS rank FROM r) WHERE rank <= 20)"
_SLICE_SQL = (_SLICES, S.grow("p2", DAYGAP), f"p2 AS MATERIALIZED ({S.serial2(DAYGAP)})")


def _slices(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[str]]:
    """The slices as streams, and the types of their days: more than SLICE_TYPES of them where there are more."""
    ev, day = T.load(spark, sf_dir, "events"), F.to_date("ts")
    seen = ev.groupBy(F.col("event_type").cast("string").alias("etype")).agg(F.max(day).alias("d")).orderBy(F.desc_nulls_last("d")).limit(SLICE_TYPES + 2).collect()
    last = seen[0]["d"] if seen else None
    types = sorted(r["etype"] for r in seen if r["etype"] is not None and r["d"] and (last - r["d"]).days < 5)
    kept = ev.where((day > F.date_sub(F.lit(last), 5)) & ~((F.col("user_id") % 6 == 5) & (day == F.lit(last))))
    return T.as_stream(kept, T.EventStreamSpec("concat(user_id % 6, '-', cast(cast(ts as date) as string))", "event_type", "ts", "event_id")), types


def _slice_tops(s: DataFrame, types: list[str]) -> DataFrame:
    """Top episodes of three nodes of each slice, with their types. A slice is a part of a date, so that all of it is within
    the gap, and its hours are counted on their own; joining its events would grow with the square of their number."""
    gap = Gap(0, 24 * HOUR, "(0,24h]")
    if len(types) <= SLICE_TYPES:
        counts = orders.count_by_stream(s, types, 3, gap, HOUR)
    else:
        s = miner._cut(s)
        grown = miner._cut(significance._grow_all(miner._cut(occurrences.serial_pairs(s, gap)), s, (gap,)))
        counts = frequency.count_by_stream(grown, gap.hi)
    counts = counts.withColumnRenamed("stream", "slice")
    return measures.top_by_slice(counts, TOP).withColumn("types", F.split("ep_id", r"-\(0,24h\]->"))


def _top_lists(s: DataFrame, types: list[str]) -> DataFrame:
    """(slice, sets): the types of each slice's top episodes."""
    return _slice_tops(s, types).groupBy("slice").agg(F.collect_list("types").alias("sets"))


@query(S.counted(*_SLICE_SQL, "SELECT slice, ep_id, freq, CAST(rank AS INTEGER) AS rank FROM q", _TOP_SQL))
def top_episodes_by_slice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _slice_tops(*_slices(spark, sf_dir)).select("slice", "ep_id", "freq", "rank")


_PEEL = """e3 AS (SELECT slice, string_split(ep_id, '-(0,24h]->') AS t FROM q),
prs AS (SELECT a.slice AS a, b.slice AS b FROM (SELECT DISTINCT slice FROM e3) AS a, (SELECT DISTINCT slice FROM e3) AS b),
l3 AS (SELECT DISTINCT a, b, t FROM prs JOIN e3 ON slice = a), r3 AS (SELECT DISTINCT a, b, t FROM prs JOIN e3 ON slice = b),
c3 AS (SELECT * FROM l3 INTERSECT SELECT * FROM r3),
l2 AS (SELECT DISTINCT a, b, unnest([t[1:2], t[2:3]]) AS t FROM (SELECT * FROM l3 EXCEPT SELECT * FROM c3)), r2 AS (SELECT DISTINCT a, b, unnest([t[1:2], t[2:3]]) AS t FROM (SELECT * FROM r3 EXCEPT SELECT * FROM c3)),
c2 AS (SELECT * FROM l2 INTERSECT SELECT * FROM r2),
l1 AS (SELECT DISTINCT a, b, unnest([t[1:1], t[2:2]]) AS t FROM (SELECT * FROM l2 EXCEPT SELECT * FROM c2)), r1 AS (SELECT DISTINCT a, b, unnest([t[1:1], t[2:2]]) AS t FROM (SELECT * FROM r2 EXCEPT SELECT * FROM c2)),
c1 AS (SELECT * FROM l1 INTERSECT SELECT * FROM r1),
tot AS (SELECT a, b, 8 AS v FROM c3 UNION ALL SELECT a, b, 4 FROM c2 UNION ALL SELECT a, b, 2 FROM c1 UNION ALL SELECT a, b, 0 FROM prs)"""


@query(S.counted(*_SLICE_SQL, "SELECT a, b, CAST(sum(v) AS BIGINT) AS sim FROM tot GROUP BY a, b", f"{_TOP_SQL}, {_PEEL}"))
def similarity_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.peel_lists(miner._cut(_top_lists(*_slices(spark, sf_dir))), 3)


_BURSTS = f"""SELECT * FROM ({_SLICES}) UNION ALL SELECT 'burst ' || stream, etype, t, eid FROM (
  SELECT r.*, d.g FROM (SELECT *, sum(o) OVER (PARTITION BY stream ORDER BY t, eid) AS g FROM (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY stream ORDER BY t, eid) < {2 * HOUR} THEN 0 ELSE 1 END AS o FROM ({_SLICES}))) AS r
  JOIN (SELECT stream, arg_max(g, (n, -t0)) AS g FROM (SELECT stream, g, count(*) AS n, min(t) AS t0 FROM (SELECT *, sum(o) OVER (PARTITION BY stream ORDER BY t, eid) AS g FROM (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY stream ORDER BY t, eid) < {2 * HOUR} THEN 0 ELSE 1 END AS o FROM ({_SLICES}))) GROUP BY ALL HAVING count(*) >= 5) GROUP BY stream) AS d ON d.stream = r.stream AND d.g = r.g)"""
_BURST_PEEL = _PEEL.replace("SELECT a.slice AS a, b.slice AS b FROM (SELECT DISTINCT slice FROM e3) AS a, (SELECT DISTINCT slice FROM e3) AS b", "SELECT slice AS a, 'burst ' || slice AS b FROM (SELECT DISTINCT slice FROM e3) WHERE slice NOT LIKE 'burst %'")


@query(S.counted(_BURSTS, S.grow("p2", DAYGAP), f"p2 AS MATERIALIZED ({S.serial2(DAYGAP)})", "SELECT a, b, CAST(sum(v) AS BIGINT) AS sim FROM tot GROUP BY a, b", f"{_TOP_SQL}, {_BURST_PEEL}"))
def similarity_burst(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each slice against the densest burst within it."""
    s, types = _slices(spark, sf_dir)
    timed = s.withColumn("ts", F.timestamp_micros("t"))
    burst = online.densest_burst(timed, "2 hours", 5).select("stream", "start", "end")  # as many as slices
    inside, own = F.expr("ts >= start and ts < end"), F.concat(F.lit("burst "), "stream")
    both = timed.join(F.broadcast(burst), "stream", "left").withColumn("stream", F.explode(F.when(inside, F.array("stream", own)).otherwise(F.array("stream"))))
    lists = miner._cut(_top_lists(both.select("stream", "etype", "t", "eid"), types))
    pairs = lists.where("slice not like 'burst %'").select(F.col("slice").alias("a"), F.concat(F.lit("burst "), "slice").alias("b"))
    return measures.peel_lists(lists, 3, pairs)


@query("SELECT CAST(user_id AS VARCHAR) AS stream, CAST(min(ts) AS TIMESTAMP) AS start, count(*) AS n FROM (SELECT *, sum(o) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 4 HOURS THEN 0 ELSE 1 END AS o FROM events)) GROUP BY user_id, b HAVING count(*) >= 3")
def burst_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = T.load(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("stream"), "ts")
    return online.bursts(ev, "4 hours", 3).select("stream", F.col("start").cast("timestamp_ntz").alias("start"), "n")


# ---- baselines


@query(f"WITH {S.stream(S.CHANNEL)} SELECT n.etype AS x, f.etype AS y, (f.t - n.t - 1) // {S.U} AS lag, count(*) AS n FROM s AS f JOIN s AS n ON f.t > n.t AND f.t - n.t <= 5 * {S.U} GROUP BY ALL")
def cross_correlogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = T.unit(spark, sf_dir)
    return baselines.cross_correlogram(T.channels(spark, sf_dir), 5 * u, u)


_BINS = f"WITH s AS (SELECT t // (10 * {S.U}) AS b, etype FROM ({S.OVERLAY})), grid AS (SELECT unnest(range(min(b), max(b) - 0 + 1)) AS b FROM s)"


@query(f"{_BINS} SELECT round(corr(nx, ny), 6) AS r, count(*) AS bins FROM (SELECT grid.b, count(*) FILTER (etype = '23') AS nx, count(*) FILTER (etype = '0') AS ny FROM grid LEFT JOIN s ON s.b = grid.b GROUP BY grid.b)")
def lagged_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    return baselines.lagged_correlation(s, 10 * u, 0, "23", "0")


_LAGS = 4


@query(f"WITH s AS (SELECT t // (10 * {S.U}) AS b, etype FROM ({S.OVERLAY})), e AS (SELECT min(b) AS b0, max(b) AS b1 FROM s), c AS (SELECT b, etype, count(*) AS n FROM s GROUP BY ALL), g AS (SELECT unnest(range(b0, b1 + 1)) AS b FROM e), ty AS (SELECT DISTINCT etype FROM s WHERE etype IN ('23', '0', '3', '4', '9')), d AS (SELECT g.b, ty.etype, coalesce(n, 0) AS n FROM g CROSS JOIN ty LEFT JOIN c USING (b, etype)) SELECT x.etype AS x, y.etype AS y, l.lag, round(corr(x.n, y.n), 6) AS r FROM range({_LAGS}) AS l(lag), d AS x JOIN d AS y ON y.b = x.b + l.lag GROUP BY ALL")
def lagged_correlations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlation of the binned counts of every two of five channels, at every lag of up to three bins."""
    s, u = _overlay(spark, sf_dir)
    return baselines.lagged_correlations(s, 10 * u, list(range(_LAGS)), ["23", "0", "3", "4", "9"])


LISTED = (("23", "0", (4, 6)), ("3", "4", (6, 8)), ("0", "3", (2, 4)), ("7", "9", (4, 6)))


@query(S.counted(S.OVERLAY, " UNION ALL ".join(f"SELECT * FROM ({S.serial2(_sql_gaps(g))}) WHERE ep_id = '{a}-({g[0]},{g[1]}]->{b}'" for a, b, g in LISTED)))
def listed_patterns(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    return strategy.count(s, [serial((a, b), (_gaps(u, g)[0],)) for a, b, g in LISTED], strategy="auto")


def _naive(latest: bool):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s, u = _overlay(spark, sf_dir)
        eps = [serial(("23", "3", "4"), tuple(_gaps(u, (6, 8))) * 2), serial(("23", "0", "3"), (_gaps(u, (4, 6))[0], _gaps(u, (2, 4))[0]))]
        valid = strategy.count(s, eps).withColumnRenamed("freq", "valid")
        return automata.naive_count(s, eps, latest).join(valid, "ep_id", "left").na.fill(0).select("ep_id", F.col("freq").alias("naive"), "valid")

    return run


query(None, "leftmost_vs_valid")(_naive(False))
query(None, "innermost_vs_valid")(_naive(True))

_MINUTES = "SELECT CAST(user_id AS VARCHAR) AS stream, event_type AS etype, epoch_us(ts) // 60000000 AS t, event_id AS eid FROM events"


def _minutes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.user_events(spark, sf_dir).withColumn("t", F.expr("t div 60000000"))


@query(f"WITH {S.stream(_MINUTES)}, {S.near(359)}, w AS (SELECT DISTINCT stream, least(x, a) || '+' || greatest(x, a) AS ep_id, unnest(range(CAST(e // 1000000000000 AS BIGINT) - 359, CAST(s // 1000000000000 AS BIGINT) + 1)) AS w FROM near WHERE a <> x) SELECT ep_id, count(*) AS windows FROM w GROUP BY ep_id")
def window_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sliding windows of 360 minutes that hold both types."""
    return frequency.window_count(occurrences.parallel_pairs(occurrences.recents(_minutes(spark, sf_dir), 359)), 360)


@query(S.counted(S.USER, S.PAIRS, S.near(2 * HOUR)))
def exhaustive_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.enumerate_all(T.user_events(spark, sf_dir), "parallel", 2, expiry=2 * HOUR)


@query(S.counted(S.USER, S.PAIRS, S.near(6 * HOUR)))
def automata_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The one-pass kernel over many streams."""
    s = T.user_events(spark, sf_dir)
    types = sorted(r[0] for r in s.select("etype").distinct().collect())
    return automata.count(s, candidates.next_parallel([parallel((x,)) for x in types]), 6 * HOUR)


@query(S.counted(S.USER, S.grow("p2", SIX), f"p2 AS MATERIALIZED ({S.serial2(SIX)})"))
def automata_serial_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.user_events(spark, sf_dir)
    types = sorted(r[0] for r in s.select("etype").distinct().collect())
    g = (Gap(0, 6 * HOUR, "(0,6h]"),) * 2
    return automata.count(s, [serial((a, b, c), g) for a in types for b in types for c in types])


@query(f"WITH {S.stream(S.CHANNEL)}, n AS (SELECT etype, count(*) AS n FROM s GROUP BY etype) SELECT a.etype AS a, b.etype AS b, round(CAST(a.n * b.n AS DOUBLE) * {S.U} / (SELECT max(t) - min(t) FROM s), 6) AS expected FROM n AS a JOIN n AS b ON a.etype < b.etype")
def expected_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.expected_pairs(T.channels(spark, sf_dir), T.unit(spark, sf_dir))


# ---- other tables as streams


def _mine_words(spark: SparkSession, sf_dir: str, plan: EpisodePlan) -> miner.MiningResult:
    """Documents are counted where they lie, each in one task."""
    packed = T.packed_words(spark, sf_dir)
    return miner.mine(T.words(spark, sf_dir), plan, "windowed" if packed is None else "streams", packed)


@query(f"WITH d AS MATERIALIZED ({S.DOCS}) SELECT * FROM ({S.counted('SELECT * FROM d', S.serial2([('(0,10]', '0', '10')]), select='SELECT ep_id, freq FROM freq WHERE freq >= (SELECT count(*) FROM d) / 250.0')})")
def documents_motifs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ordered pairs of words within ten positions that are found once in 250 words or more; any word may take part."""
    return _mine_words(spark, sf_dir, EpisodePlan("serial", 0.004, gaps=(Gap(0, 10),), max_k=2)).frequent(spark).where("k = 2").select("ep_id", "freq")


@query()
def documents_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of up to four words with gaps of up to ten positions, by a frequency threshold over all words."""
    return _mine_words(spark, sf_dir, EpisodePlan("serial", 0.002, gaps=(Gap(0, 10),), max_k=4)).frequent(spark).where("k > 1").select("ep_id", "k", "freq")


@query()
def documents_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of up to ten words within ten positions, by a frequency threshold over all words."""
    return _mine_words(spark, sf_dir, EpisodePlan("parallel", 0.0005, expiry=9, max_k=10)).frequent(spark).where("k > 1").select("ep_id", "k", "freq")


@query(S.counted("SELECT CAST(conv_id AS VARCHAR) AS stream, role AS etype, CAST(turn AS BIGINT) AS t, CAST(turn AS BIGINT) AS eid FROM conversations WHERE role IS NOT NULL AND turn IS NOT NULL", S.serial2([("(0,1]", "0", "1")])))
def conversation_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.as_stream(T.load(spark, sf_dir, "conversations"), T.EventStreamSpec("conv_id", "role", "turn", "turn", "ticks"))
    return frequency.count(occurrences.serial_pairs(s, Gap(0, 1)))


@query(S.counted("SELECT CAST(page_id AS VARCHAR) AS stream, w AS etype, CAST(i - 1 AS BIGINT) AS t, CAST(i - 1 AS BIGINT) AS eid FROM (SELECT page_id, unnest(x) AS w, generate_subscripts(x, 1) AS i FROM (SELECT page_id, regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1) AS x FROM pages))", S.serial2([("(0,1]", "0", "1")])))
def page_tag_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    tags = T.load(spark, sf_dir, "pages").select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), F.lit(1))).alias("t", "etype"))
    s = T.as_stream(tags, T.EventStreamSpec("page_id", "etype", "t", "t", "ticks"))
    return frequency.count(occurrences.serial_pairs(s, Gap(0, 1)))


_ORDERS = "SELECT CAST(o_custkey AS VARCHAR) AS stream, o_orderpriority AS etype, datediff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS t, o_orderkey AS eid FROM orders"


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.as_stream(T.load(spark, sf_dir, "orders"), T.EventStreamSpec("o_custkey", "o_orderpriority", "o_orderdate", "o_orderkey", "days"))


@query(S.counted(_ORDERS, S.serial2([("(0,90d]", "0", "90")])))
def orders_priority_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frequency.count(occurrences.serial_pairs(_orders(spark, sf_dir), Gap(0, 90, "(0,90d]")))


@query(S.counted("SELECT CAST(l_suppkey AS VARCHAR) AS stream, p_brand AS etype, datediff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) AS t, l_orderkey * 10 + l_linenumber AS eid FROM lineitem JOIN part ON l_partkey = p_partkey", S.PAIRS, S.near(2)))
def lineitem_brand_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Brands that a supplier ships within two days: a join, many ties, a few long streams."""
    rows = T.load(spark, sf_dir, "lineitem").join(T.load(spark, sf_dir, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    s = T.as_stream(rows, T.EventStreamSpec("l_suppkey", "p_brand", "l_shipdate", "l_orderkey * 10 + l_linenumber", "days"))
    return frequency.count(occurrences.parallel_pairs(occurrences.recents(s, 2)))


_BY_CUSTOMER = S.counted(_ORDERS, S.serial2([("(0,90d]", "0", "90")]), select="SELECT CAST(stream AS BIGINT) AS c_custkey, count(*) AS freq FROM g WHERE ep_id LIKE '1-URGENT-%' GROUP BY stream")


def _by_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = frequency.count_by_stream(occurrences.serial_pairs(_orders(spark, sf_dir), Gap(0, 90, "(0,90d]"))).where("ep_id like '1-URGENT-%'")
    return c.groupBy(F.col("stream").cast("long").alias("c_custkey")).agg(F.sum("freq").alias("freq"))


@query(f"SELECT r_name, n_name, CAST(sum(freq) AS BIGINT) AS freq FROM ({_BY_CUSTOMER}) JOIN customer USING (c_custkey) JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def freq_rollup_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = T.load(spark, sf_dir, "nation").join(F.broadcast(T.load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    rows = _by_customer(spark, sf_dir).join(T.load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), "c_custkey").join(F.broadcast(names), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.rollup("r_name", "n_name").agg(F.sum("freq").alias("freq"))


@query(f"SELECT c_mktsegment, c_nationkey, CAST(sum(freq) AS BIGINT) AS freq FROM ({_BY_CUSTOMER}) JOIN customer USING (c_custkey) GROUP BY CUBE (c_mktsegment, c_nationkey)")
def freq_cube_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _by_customer(spark, sf_dir).join(T.load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", "c_nationkey"), "c_custkey")
    return rows.cube("c_mktsegment", "c_nationkey").agg(F.sum("freq").alias("freq"))


# ---- relational operators and the SQL surface


@query("SELECT f.event_id AS eid, max(n.event_id) AS last_click FROM events AS f LEFT JOIN events AS n ON n.user_id = f.user_id AND n.event_type = 'click' AND n.ts < f.ts WHERE f.event_type = 'purchase' GROUP BY 1")
def asof_last_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each purchase the user's last click before it: a window, no join in time."""
    s = T.user_events(spark, sf_dir).where("etype in ('click', 'purchase')")
    w = W.partitionBy("stream").orderBy("t").rangeBetween(W.unboundedPreceding, -1)
    last = F.max(F.when(F.col("etype") == "click", F.struct("t", "eid"))).over(w)
    return s.withColumn("l", last).where("etype = 'purchase'").select("eid", F.col("l.eid").alias("last_click"))


@query(f"SELECT n.event_type AS a, f.event_type AS b, count(*) AS n FROM events AS f JOIN events AS n ON n.user_id = f.user_id AND epoch_us(f.ts) - epoch_us(n.ts) > {HOUR} AND epoch_us(f.ts) - epoch_us(n.ts) <= {3 * HOUR} GROUP BY ALL")
def band_join_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = T.user_events(spark, sf_dir)
    return occurrences.band_join(s, s, HOUR, 3 * HOUR).groupBy(F.col("l.etype").alias("a"), F.col("r.etype").alias("b")).agg(F.count("*").alias("n"))


@query("WITH a AS (SELECT DISTINCT event_type AS x FROM events WHERE user_id % 2 = 0), b AS (SELECT DISTINCT event_type AS x FROM events WHERE user_id % 3 = 0) SELECT 'both' AS part, x FROM (SELECT x FROM a INTERSECT SELECT x FROM b) UNION ALL SELECT 'any', x FROM (SELECT x FROM a UNION SELECT x FROM b) UNION ALL SELECT 'less', x FROM (SELECT x FROM a EXCEPT SELECT x FROM b)")
def set_ops_episodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = T.load(spark, sf_dir, "events")
    a, b = (ev.where(F.col("user_id") % k == 0).select(F.col("event_type").alias("x")).distinct() for k in (2, 3))
    named = lambda df, n: df.select(F.lit(n).alias("part"), "x")
    return named(a.intersect(b), "both").unionByName(named(a.union(b).distinct(), "any")).unionByName(named(a.subtract(b), "less"))


@query("SELECT event_type || '/' || (CAST(json_extract(props, '$.k') AS BIGINT) % 3) AS etype, count(*) AS n FROM events GROUP BY 1")
def json_props_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    sub = F.get_json_object("props", "$.k").cast("long") % 3
    return T.load(spark, sf_dir, "events").select(F.concat_ws("/", "event_type", sub.cast("string")).alias("etype")).groupBy("etype").agg(F.count("*").alias("n"))


@query(S.counted(S.USER, S.serial2(SIX), select="SELECT 'click>purchase' AS ep_id, freq FROM freq WHERE ep_id = 'click-(0,6h]->purchase'"))
def udtf_occurrences(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    T.user_events(spark, sf_dir).createOrReplaceTempView("episode_stream")
    return spark.sql(f"SELECT ep_id, sum(freq) AS freq FROM episode_occurrences(TABLE(episode_stream) PARTITION BY stream ORDER BY (t, eid), 'click>purchase', 0, {6 * HOUR}) GROUP BY ep_id")


@query("WITH RECURSIVE s AS MATERIALIZED (SELECT event_type AS etype, user_id AS u, epoch_us(ts) AS t FROM events), k(etype, u, t) AS (SELECT etype, u, min(t) FROM s GROUP BY ALL UNION ALL SELECT k.etype, k.u, min(s.t) FROM k JOIN s ON s.etype = k.etype AND s.u = k.u AND s.t - k.t >= 7200000000 GROUP BY k.etype, k.u) SELECT etype, count(*) AS kept FROM k GROUP BY etype")
def refractory_thinning(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simulator.refractory(T.user_events(spark, sf_dir), 2 * HOUR).groupBy("etype").agg(F.count("*").alias("kept"))


@query("SELECT event_type AS etype, count(DISTINCT user_id) AS users, round(var_samp(c) / avg(c), 6) AS fano FROM (SELECT event_type, user_id, count(*) AS c FROM events GROUP BY ALL) GROUP BY 1")
def dispersion(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = T.user_events(spark, sf_dir).groupBy("etype", "stream").agg(F.count("*").alias("c"))
    return c.groupBy("etype").agg(F.count("*").alias("users"), F.round(F.var_samp("c") / F.avg("c"), 6).alias("fano"))


_AT = "(SELECT count(*) FROM s) / 100.0"


@query(S.counted(S.OVERLAY, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U), "SELECT CAST(k AS INTEGER) AS k, n_candidates, n_frequent, max_freq, min_freq FROM l", f"o AS (SELECT etype, count(*) AS f FROM s GROUP BY 1), p AS (SELECT split_part(ep_id, '+', 1) AS x, split_part(ep_id, '+', 2) AS y, freq FROM freq WHERE ep_id NOT LIKE '%+%+%' AND freq >= {_AT}), c AS (SELECT a.x, a.y, b.y AS z FROM p AS a JOIN p AS b ON a.x = b.x AND a.y < b.y JOIN p AS d ON d.x = a.y AND d.y = b.y), q AS (SELECT freq FROM freq JOIN c ON ep_id = x || '+' || y || '+' || z WHERE freq >= {_AT}), l AS (SELECT 1 AS k, (SELECT count(*) FROM o) AS n_candidates, count(*) AS n_frequent, max(f) AS max_freq, min(f) AS min_freq FROM o WHERE f >= {_AT} UNION ALL SELECT 2, (SELECT count(*) * (count(*) - 1) // 2 FROM o WHERE f >= {_AT}), count(*), max(freq), min(freq) FROM p UNION ALL SELECT 3, (SELECT count(*) FROM c), count(*), max(freq), min(freq) FROM q)"))
def level_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates, frequent episodes and their counts of each of the first three levels: a pass over the data for each."""
    s, u = _overlay(spark, sf_dir)
    return mine(s, EpisodePlan("parallel", 0.01, expiry=u, max_k=3)).level_stats(spark).drop("wall_ms")


@query(S.counted(S.OVERLAY, f"{S.PAIRS} UNION ALL {S.TRIPLES}", S.near(S.U), "SELECT CAST(max(k) AS INTEGER) AS largest, count(*) FILTER (k = (SELECT max(k) FROM h)) AS of_that_size, max(k) AS passes FROM h", f"h AS (SELECT len(string_split(ep_id, '+')) AS k FROM freq WHERE freq >= {_AT})"))
def largest_found(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest size, how many episodes have it, and the passes over the data."""
    s, u = _overlay(spark, sf_dir)
    found = mine(s, EpisodePlan("parallel", 0.01, expiry=u))
    return spark.createDataFrame([(*found.largest(), found.passes)], "largest int, of_that_size long, passes long")


@query()
def peak_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the one-pass kernel remembers at most of each episode: entries within the gaps, however long the stream is."""
    s, g = T.user_events(spark, sf_dir), Gap(0, 6 * HOUR, "(0,6h]")
    eps = [serial(("click", "view"), (g,)), serial(("click", "view", "purchase"), (g, g)), serial(("error", "error"), (g,))]
    return automata.count_by_stream(s, eps).groupBy("ep_id").agg(F.max("peak_entries").alias("peak_entries"), F.sum("freq").alias("freq"))


@query()
def level_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates, frequent episodes and seconds of each level, beside the number of combinations."""
    s, u = _overlay(spark, sf_dir)
    found = mine(s, EpisodePlan("parallel", 0.01, expiry=u))
    return found.level_stats(spark).withColumn("combinations", F.pow(F.lit(26.0), "k"))


def _rates_option(spark: SparkSession, sf_dir: str) -> str:
    return ",".join(f"{i}:{x!r}" for i, x in sorted(_unit_rates(spark, sf_dir, 26).items()))


@query()
def spike_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The simulator read as a data source, its units at the rates of the events' channels."""
    from .sources import spikes

    spikes.register(spark)
    return spark.read.format("spikes").options(n="26", seconds="2", datasets="2", order="0,1,2,3", rates=_rates_option(spark, sf_dir)).load().groupBy("stream", "etype").agg(F.count("*").alias("n"))


def _replay(spark: SparkSession, sf_dir: str, eps: list[Episode], expiry: int | None) -> DataFrame:
    """Each stream's last online count of each episode, after a replay of all events."""
    ev = spark.readStream.schema(T.load(spark, sf_dir, "events").schema).parquet(f"{sf_dir.rstrip('/')}/events.parquet*")
    timed = T.as_stream(ev, T.EventStreamSpec("user_id", "event_type", "ts", "event_id")).withColumn("ts", F.timestamp_micros("t"))
    path, timed = new_path(spark, "online"), online.closed(timed, new_path(spark, "closing"))
    counts = online.online_count(timed, eps, expiry).writeStream.outputMode("update").foreachBatch(online.batch_sink(path))
    counts.option("checkpointLocation", new_path(spark, "online-progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(online.OUT).parquet(path).groupBy("stream", "ep_id").agg(F.max("freq").alias("freq"))


_LAST_COUNTS = "SELECT stream, ep_id, count(*) AS freq FROM g WHERE ep_id IN ({}) GROUP BY ALL"


@query(S.counted(S.USER, S.PAIRS, S.near(6 * HOUR), _LAST_COUNTS.format("'click+purchase', 'click+view'")))
def online_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running counts over a replay of all events; each stream's last count of each episode."""
    return _replay(spark, sf_dir, [parallel(("click", "purchase")), parallel(("click", "view"))], 6 * HOUR)


@query(S.counted(S.USER, S.serial2(SIX), select=_LAST_COUNTS.format("'view-(0,6h]->click', 'click-(0,6h]->purchase'")))
def online_serial_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders counted online, by lists of times of which what is out of reach is dropped."""
    return _replay(spark, sf_dir, [serial(x, (THREE_GAPS[0],)) for x in (("view", "click"), ("click", "purchase"))], None)


@query()
def spike_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The data source read as a stream."""
    from .sources import spikes

    spikes.register(spark)
    path = new_path(spark, "spikes")
    live = spark.readStream.format("spikes").options(n="26", seconds="2", datasets="2", order="0,1,2,3", rates=_rates_option(spark, sf_dir)).load()
    live.writeStream.foreachBatch(online.batch_sink(path)).option("checkpointLocation", new_path(spark, "spikes-progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(live.schema).parquet(path).groupBy("stream", "etype").agg(F.count("*").alias("n"))


# ---- more operators around the methods


@query(S.counted(S.USER, S.serial2(SIX)))
def nonoverlap_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The grouped aggregate in Python instead of the fold in the JVM; events have unique times here."""
    raw = occurrences.serial_pairs(T.user_events(spark, sf_dir), Gap(0, 6 * HOUR, "(0,6h]"))
    per = raw.select("stream", "ep_id", F.col("s.t").alias("s"), F.col("e.t").alias("e")).groupBy("stream", "ep_id").agg(udfs.nonoverlap_count("s", "e").alias("n"))
    return per.groupBy("ep_id").agg(F.sum("n").alias("freq"))


@query(S.counted(*_SLICE_SQL, "SELECT slice, ep_id, len(list_filter([1, 2], lambda i: t[i] = 'click' AND list_contains(t[i + 1:], 'view'))) > 0 AS holds FROM (SELECT *, string_split(ep_id, '-(0,24h]->') AS t FROM q)", _TOP_SQL))
def subepisode_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _slice_tops(*_slices(spark, sf_dir)).select("slice", "ep_id", udfs.is_subepisode(F.array(F.lit("click"), F.lit("view")), F.col("types")).alias("holds"))


@query(S.counted(S.OVERLAY, _GROUP_SQL, S.near(S.U), "SELECT etype, count(*) AS n FROM (SELECT etype FROM s UNION ALL SELECT '[0 1 2]' FROM c) GROUP BY etype", f"{_MEMBERS}, {_COMPOUND.format(_ANCHORS['midpoint'])}"))
def chain_rewrite_augment(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, u = _overlay(spark, sf_dir)
    return compound.rewrite(s, compound.track(s, [parallel(GROUP.split("+"))], u, _chunk(u, u)), mode="augment").groupBy("etype").agg(F.count("*").alias("n"))


@query(S.counted(S.USER, S.PAIRS, S.near(f"{6 * HOUR} - 1")))
def parallel_pairs_strict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans strictly below the expiry."""
    return frequency.count(occurrences.parallel_pairs(occurrences.recents(T.user_events(spark, sf_dir), 6 * HOUR, strict=True)))


@query("SELECT etype, freq, rank() OVER (ORDER BY freq DESC) AS r, dense_rank() OVER (ORDER BY freq DESC) AS d, ntile(4) OVER (ORDER BY freq DESC, etype) AS q, round(percent_rank() OVER (ORDER BY freq DESC), 6) AS p, round(cume_dist() OVER (ORDER BY freq DESC), 6) AS c FROM (SELECT CAST(user_id % 26 AS VARCHAR) AS etype, count(*) AS freq FROM events GROUP BY 1)")
def ranking_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Over channels, of which there are 26 however long the stream is."""
    c = T.channels(spark, sf_dir).groupBy("etype").agg(F.count("*").alias("freq"))
    w, tied = W.orderBy(F.desc("freq")), W.orderBy(F.desc("freq"), "etype")
    return c.select("etype", "freq", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(tied).alias("q"), F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@query("SELECT etype, count(*) FILTER (g = 0) AS g0, count(*) FILTER (g = 1) AS g1, count(*) FILTER (g = 2) AS g2 FROM (SELECT event_type AS etype, user_id % 3 AS g FROM events) GROUP BY 1")
def cohort_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = T.load(spark, sf_dir, "events").select(F.col("event_type").alias("etype"), F.concat(F.lit("g"), F.col("user_id") % 3).alias("g"))
    return rows.groupBy("etype").pivot("g", ["g0", "g1", "g2"]).count().na.fill(0)


@query("SELECT etype, g, count(*) AS n FROM (SELECT event_type AS etype, 'g' || (user_id % 3) AS g FROM events) GROUP BY ALL")
def cohort_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cohort_pivot(spark, sf_dir).unpivot("etype", ["g0", "g1", "g2"], "g", "n").where("n > 0")


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")
def priority_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    T.load(spark, sf_dir, "orders").createOrReplaceTempView("episode_orders")
    return spark.sql("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM episode_orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")


@query("SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def alphabet_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_partkey").alias("parts"))


@query("SELECT event_type AS etype, count(*) AS n FROM events GROUP BY 1")
def dedupe_spikes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.dedupe(T.merge_streams(T.user_events(spark, sf_dir), T.user_events(spark, sf_dir))).groupBy("etype").agg(F.count("*").alias("n"))


@query("SELECT event_type AS etype, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-20' GROUP BY 1")
def time_slice(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = T.load(spark, sf_dir, "events").where("ts >= timestamp_ntz'2024-01-10' and ts < timestamp_ntz'2024-01-20'")
    return ev.groupBy(F.col("event_type").alias("etype")).agg(F.count("*").alias("n"))


@query(S.counted(S.CHANNEL, S.serial2(_sql_gaps((4, 6))), select="SELECT ep_id, freq FROM freq ORDER BY freq DESC, ep_id LIMIT 10"))
def top_episodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = T.unit(spark, sf_dir)
    return frequency.count(occurrences.serial_pairs(T.channels(spark, sf_dir), _gaps(u, (4, 6))[0]), _chunk(u, 6 * u)).orderBy(F.desc("freq"), "ep_id").limit(10)


@query("SELECT event_type AS etype, CAST(w AS TIMESTAMP) AS start, count(*) AS n FROM (SELECT event_type, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS w FROM events) GROUP BY ALL")
def sliding_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = T.load(spark, sf_dir, "events").select(F.col("event_type").alias("etype"), "ts")
    return ev.groupBy("etype", F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select("etype", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query(S.counted(S.OVERLAY, S.serial2(_sql_gaps(*FIVE)), select="SELECT a.ep_id AS fixed, a.freq AS fixed_freq, b.ep_id AS discovered, b.freq AS discovered_freq FROM (SELECT * FROM freq WHERE ep_id LIKE '%(4,6]%' AND freq >= 100) AS a JOIN (SELECT * FROM (SELECT *, split_part(ep_id, '-', 1) || '>' || split_part(ep_id, '->', 2) AS ty, row_number() OVER (PARTITION BY split_part(ep_id, '-', 1), split_part(ep_id, '->', 2) ORDER BY freq DESC, ep_id) AS r FROM freq) WHERE r = 1) AS b ON b.ty = split_part(a.ep_id, '-', 1) || '>' || split_part(a.ep_id, '->', 2)"))
def fixed_vs_discovered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What one interval finds, beside the best of five intervals for the same types."""
    s, u = _overlay(spark, sf_dir)
    found = mine(s, EpisodePlan("serial", 0, gaps=tuple(_gaps(u, *FIVE)), max_k=2)).frequent(spark).where("k = 2")
    best = miner.best_intervals(found).select("types", F.col("ep_id").alias("discovered"), F.col("freq").alias("discovered_freq"))
    fixed = found.where("gaps[0] = '(4,6]' and freq >= 100").select("types", F.col("ep_id").alias("fixed"), F.col("freq").alias("fixed_freq"))
    return fixed.join(best, "types").select("fixed", "fixed_freq", "discovered", "discovered_freq")


@query("WITH q AS (SELECT doc_id, quality FROM labels WHERE quality IS NOT NULL), s AS (SELECT quality, count(*) AS docs, CAST(sum(len(regexp_split_to_array(lower(coalesce(text, '')), '[^a-z]+'))) AS BIGINT) AS parts FROM documents JOIN q USING (doc_id) GROUP BY 1) SELECT * FROM s")
def cohort_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = T.load(spark, sf_dir, "labels").where("quality is not null").select("doc_id", "quality")
    d = T.load(spark, sf_dir, "documents").select("doc_id", F.size(F.split(F.lower(F.coalesce("text", F.lit(""))), r"[^a-z]+")).alias("w"))
    return d.join(q, "doc_id").groupBy("quality").agg(F.count("*").alias("docs"), F.sum("w").alias("parts"))


@query()
def simulate_average(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recovery of planted orders, averaged over data sets."""
    runs, own = [], _unit_rates(spark, sf_dir, 32)
    for k in range(3):
        net = simulator.Network(32, simulator.random_network(32, 2, 0.5, 20 + k), dict(own))
        for b in _blocks(2, 6):
            simulator.plant(net, [[i] for i in b])
        runs.append(_planted_run(spark, net, EpisodePlan("serial", 60, gaps=(Gap(4000, 6000),), max_k=6), 12))
    return measures.average_runs(runs)


@query()
def alphabet_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Approximate sizes and quantiles, flagged as such."""
    li = T.load(spark, sf_dir, "lineitem")
    return li.groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("approx_parts"), F.percentile_approx("l_quantity", 0.5).alias("approx_median"))


@query(S.counted(S.CHANNEL, S.serial2(_sql_gaps((4, 6)))))
def chunked_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One long stream whose islands are found chunk by chunk of time."""
    u = T.unit(spark, sf_dir)
    return frequency.count(occurrences.serial_pairs(T.channels(spark, sf_dir), _gaps(u, (4, 6))[0]), _chunk(u, 6 * u))


@query(S.counted(S.USER, f"SELECT f.stream, 'x' AS ep_id, least(max(n.p) FILTER (n.etype = 'click'), max(n.p) FILTER (n.etype = 'view')) AS s, f.p AS e FROM s AS f JOIN s AS n ON n.stream = f.stream AND n.t < f.t AND f.t - n.t <= {24 * HOUR} WHERE f.etype = 'purchase' GROUP BY f.stream, f.p HAVING count(*) FILTER (n.etype = 'click') > 0 AND count(*) FILTER (n.etype = 'view') > 0", select="SELECT freq FROM freq"))
def general_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A click and a view in any order, then a purchase, within a day."""
    return automata.count_order(T.user_events(spark, sf_dir), ["click", "view", "purchase"], [(0, 2), (1, 2)], 24 * HOUR)


# ---- join, window and sampling forms


@query(S.counted(S.USER, S.serial2(THREE), select="SELECT a.ep_id || substr(b.ep_id, length(b.x) + 1) AS ep_id FROM p AS a JOIN p AS b ON a.y = b.x", more="p AS (SELECT ep_id, split_part(ep_id, '-', 1) AS x, split_part(ep_id, '->', 2) AS y FROM freq WHERE freq >= 300)"))
def candidates_by_merge_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overlap join of many candidates: both sides sorted, nothing broadcast."""
    found = mine(T.user_events(spark, sf_dir), EpisodePlan("serial", 300, gaps=THREE_GAPS, max_k=2)).frequent(spark).where("k = 2")
    a = found.select(F.col("ep_id").alias("id"), F.get("types", F.lit(1)).alias("key"))
    b = found.select(F.get("types", F.lit(0)).alias("key"), F.expr("substr(ep_id, length(types[0]) + 1)").alias("rest"))
    return a.join(b.hint("merge"), "key").select(F.concat("id", "rest").alias("ep_id"))


@query("SELECT n_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def streams_by_hash_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events to the dimensions of their streams: a hash table a partition, without sorting the large side."""
    c = T.load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    rows = T.load(spark, sf_dir, "orders").select("o_custkey").join(c.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey"))
    return rows.join(F.broadcast(T.load(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("WITH e AS (SELECT event_type AS etype, count(*) AS freq FROM events GROUP BY 1) SELECT a.etype AS a, b.etype AS b FROM e AS a JOIN e AS b ON a.freq > b.freq")
def more_frequent_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A join by inequality, over the alphabet alone."""
    c = T.user_events(spark, sf_dir).groupBy("etype").agg(F.count("*").alias("freq"))
    return c.alias("a").join(c.alias("b"), F.col("a.freq") > F.col("b.freq")).select(F.col("a.etype").alias("a"), F.col("b.etype").alias("b"))


@query("SELECT event_id AS eid, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER w AS last_click, first_value(event_type) OVER w AS first_type, nth_value(event_type, 2) OVER w AS second_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
def latest_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a stream has seen up to each event: its latest click, its first and its second type."""
    w = W.partitionBy("stream").orderBy("t", "eid").rowsBetween(W.unboundedPreceding, 0)
    click = F.when(F.col("etype") == "click", F.col("eid"))
    return T.user_events(spark, sf_dir).select("eid", F.last(click, ignorenulls=True).over(w).alias("last_click"), F.first("etype").over(w).alias("first_type"), F.nth_value("etype", 2).over(w).alias("second_type"))


_COMBINATIONS = "WITH RECURSIVE r(k, combinations, m) AS (SELECT 1, m, m FROM (SELECT count(DISTINCT event_type) AS m FROM {0}) AS e WHERE m > 0 UNION ALL SELECT k + 1, combinations * m, m FROM r WHERE k < 6) SELECT k, combinations FROM r"


@query(_COMBINATIONS.format("events"))
def combinations_by_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many orders of each size the types of the events allow, by a recursive query."""
    T.load(spark, sf_dir, "events").select("event_type").createOrReplaceTempView("episode_types")
    return spark.sql(_COMBINATIONS.format("episode_types"))


@query()
def sampled_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An estimate of each type's frequency from a tenth of the streams, flagged as such: a probe for thresholds."""
    s = T.user_events(spark, sf_dir)
    some = s.join(s.select("stream").distinct().sample(0.1, 7), "stream", "left_semi")
    return some.groupBy("etype").agg((F.count("*") * 10).alias("approx_freq"))
