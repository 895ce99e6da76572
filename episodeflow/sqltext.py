"""DuckDB SQL for the registered queries, written from the definitions: enumerate reachable intervals by self-joins, then
jump from each chosen interval to the one that ends first after it."""

from __future__ import annotations

U = "(SELECT 1350000000000 // count(*) FROM events)"
HOUR = 3_600_000_000
USER = "SELECT CAST(user_id AS VARCHAR) AS stream, event_type AS etype, epoch_us(ts) AS t, event_id AS eid FROM events"
CHANNEL = "SELECT 'all' AS stream, CAST(user_id % 26 AS VARCHAR) AS etype, epoch_us(ts) AS t, event_id AS eid FROM events"
NODES = "(VALUES (0,23,0),(1,0,5),(2,1,5),(3,2,5),(4,3,8),(5,4,15),(6,5,18))"


def overlay(seed: int = 0) -> str:
    return f"""{CHANNEL} UNION ALL
  SELECT 'all', CAST(c AS VARCHAR), epoch_us(ts) + d * {U} + ((event_id // 40 * 53 + i * 29 + {seed * 7}) % 61 - 30) * 1000000, 1000000000 + 10 * (event_id // 40) + i
  FROM events, {NODES} AS n(i, c, d) WHERE event_id % 40 = 0 AND (event_id // 40 * 37 + i * 11 + {seed}) % 100 >= 5"""


OVERLAY = overlay()
DOCS = """SELECT CAST(doc_id AS VARCHAR) AS stream, w AS etype, CAST(i - 1 AS BIGINT) AS t, CAST(i - 1 AS BIGINT) AS eid FROM
  (SELECT doc_id, unnest(x) AS w, generate_subscripts(x, 1) AS i FROM (SELECT doc_id, regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{L}]+') AS x FROM documents)) WHERE w <> ''"""


def stream(source: str) -> str:
    return f"s AS MATERIALIZED (SELECT stream, etype, t, eid, CAST(t AS HUGEINT) * 1000000000000 + eid AS p FROM ({source}))"


def near(expiry) -> str:
    return f"near AS MATERIALIZED (SELECT f.stream, f.etype AS x, f.p AS e, n.etype AS a, max(n.p) AS s FROM s AS f JOIN s AS n ON n.stream = f.stream AND n.t >= f.t - ({expiry}) AND n.p <= f.p GROUP BY ALL)"


PAIRS = "SELECT stream, least(x, a) || '+' || greatest(x, a) AS ep_id, s, e FROM near WHERE a <> x"
TRIPLES = "SELECT m.stream, array_to_string(list_sort([m.x, m.a, n.a]), '+') AS ep_id, least(m.s, n.s) AS s, m.e FROM near AS m JOIN near AS n ON m.stream = n.stream AND m.e = n.e AND m.x = n.x AND m.a < n.a WHERE m.a <> m.x AND n.a <> n.x"
QUADS = "SELECT m.stream, array_to_string(list_sort([m.x, m.a, n.a, o.a]), '+') AS ep_id, least(m.s, n.s, o.s) AS s, m.e FROM near AS m JOIN near AS n ON m.stream = n.stream AND m.e = n.e AND m.x = n.x AND m.a < n.a JOIN near AS o ON m.stream = o.stream AND m.e = o.e AND m.x = o.x AND n.a < o.a WHERE m.a <> m.x AND n.a <> n.x AND o.a <> o.x"


def serial2(gaps: list[tuple[str, str, str]]) -> str:
    """gaps: (label, lo, hi)."""
    return " UNION ALL ".join(f"SELECT f.stream, n.etype || '-{g}->' || f.etype AS ep_id, max(n.p) AS s, f.p AS e, f.t AS et FROM s AS f JOIN s AS n ON n.stream = f.stream AND f.t - n.t > {lo} AND f.t - n.t <= {hi} GROUP BY f.stream, n.etype, f.etype, f.p, f.t" for g, lo, hi in gaps)


def grow(prefix: str, gaps: list[tuple[str, str, str]], where: str = "true") -> str:
    return " UNION ALL ".join(f"SELECT f.stream, n.ep_id || '-{g}->' || f.etype AS ep_id, max(n.s) AS s, f.p AS e, f.t AS et FROM s AS f JOIN {prefix} AS n ON n.stream = f.stream AND f.t - n.et > {lo} AND f.t - n.et <= {hi} WHERE {where} GROUP BY f.stream, n.ep_id, f.etype, f.p, f.t" for g, lo, hi in gaps)


CHOOSE = """g(stream, ep_id, e) AS (
  SELECT stream, ep_id, min(e) FROM iv GROUP BY stream, ep_id
  UNION ALL SELECT g.stream, g.ep_id, min(iv.e) FROM g JOIN iv ON iv.stream = g.stream AND iv.ep_id = g.ep_id AND iv.s > g.e GROUP BY g.stream, g.ep_id
)"""
FREQ = "freq AS (SELECT ep_id, count(*) AS freq FROM g GROUP BY ep_id)"


def counted(source: str, intervals: str, before: str = "", select: str = "SELECT ep_id, freq FROM freq", more: str = "") -> str:
    return f"WITH RECURSIVE {stream(source)}, {before + ',' if before else ''} iv AS MATERIALIZED ({intervals}), {CHOOSE}, {FREQ}{', ' + more if more else ''} {select}"
