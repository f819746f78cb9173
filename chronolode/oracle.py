"""SQL texts for DuckDB that give the same rows as the queries: plain enumeration, no pruning."""

from __future__ import annotations

HOUR = "date_diff('hour', TIMESTAMP '2024-01-01', ts) + 1"
MINUTE = "date_diff('minute', TIMESTAMP '2024-01-01', ts) + 1"
CENTS = "round(value * 100)::BIGINT"

CES = {
    "hours": f"SELECT ({HOUR})::BIGINT AS t, event_type AS item, sum({CENTS})::BIGINT AS u FROM events WHERE {CENTS} > 0 GROUP BY 1, 2",
    "minutes": f"SELECT ({MINUTE})::BIGINT AS t, event_type AS item, sum({CENTS})::BIGINT AS u FROM events WHERE {CENTS} > 0 GROUP BY 1, 2",
    "orders": "SELECT (l_orderkey + 1)::BIGINT AS t, lpad(l_partkey::VARCHAR, 8, '0') AS item, sum(l_quantity::BIGINT * round(p_retailprice * 100)::BIGINT)::BIGINT AS u FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1, 2",
    "brands": "SELECT (date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) + 1)::BIGINT AS t, p_brand AS item, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS u FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN part ON p_partkey = l_partkey WHERE round(l_extendedprice * 100) > 0 GROUP BY 1, 2",
    "props": f"SELECT ({HOUR})::BIGINT AS t, event_type AS item, sum((props->>'$.k')::BIGINT)::BIGINT AS u FROM events WHERE (props->>'$.k')::BIGINT > 0 GROUP BY 1, 2",
    "example": "SELECT t::BIGINT AS t, item, u::BIGINT AS u FROM (VALUES (1, 'A', 2), (2, 'B', 2), (2, 'D', 2), (3, 'B', 3), (3, 'C', 3), (4, 'A', 4), (4, 'C', 3), (5, 'D', 2)) AS x(t, item, u)",
    "late_partner": "SELECT t::BIGINT AS t, item, u::BIGINT AS u FROM (VALUES (1, 'A', 1), (2, 'B', 1), (3, 'B', 1), (3, 'C', 1)) AS x(t, item, u)",
    "users": f"SELECT user_id AS seq_id, ({MINUTE})::BIGINT AS t, event_type AS item, sum({CENTS})::BIGINT AS u FROM events WHERE {CENTS} > 0 GROUP BY 1, 2, 3",
}


def enumerated(ces: str, width: int, max_len: int | None = None, kinds: str = "all", by_sequence: bool = False) -> str:
    """WITH clauses that end in ep(episode, events, sets, utility, frequency): every episode within the width."""
    allowed = {"all": "(c.t > g.te OR c.item > g.last)", "serial": "c.t > g.te", "simultaneous": "c.t = g.te AND c.item > g.last"}[kinds]
    limit = f"WHERE g.n < {max_len}" if max_len else ""
    seq, own = ("seq_id", "c.seq_id = g.seq_id AND") if by_sequence else ("0", "")
    return f"""
WITH RECURSIVE ces AS ({ces}),
g(seq_id, ep, ts, te, last, u, times, n, m) AS (
  SELECT {seq}, item, t, t, item, u, [t], 1, 1 FROM ces
  UNION ALL
  SELECT g.seq_id, CASE WHEN c.t = g.te THEN g.ep || '+' || c.item ELSE g.ep || '>' || c.item END, g.ts, c.t, c.item, g.u + c.u,
    CASE WHEN c.t = g.te THEN g.times ELSE list_append(g.times, c.t) END, g.n + 1, CASE WHEN c.t = g.te THEN g.m ELSE g.m + 1 END
  FROM g JOIN ces c ON {own} c.t >= g.te AND c.t <= g.ts + {width} AND {allowed} {limit}),
o AS (SELECT *, row_number() OVER (PARTITION BY seq_id, ep, ts ORDER BY te, times) AS r FROM g),
f AS (SELECT *, lead(te) OVER (PARTITION BY seq_id, ep ORDER BY ts) AS nxt FROM o WHERE r = 1),
ep AS (SELECT ep AS episode, n::INTEGER AS events, m::INTEGER AS sets, sum(u)::BIGINT AS utility, count(*)::BIGINT AS frequency FROM f WHERE nxt IS NULL OR nxt > te GROUP BY ep, n, m)
"""


def top_k(ces: str, width: int, k: int, max_len: int | None = None, kinds: str = "all", by: str = "utility", ties: str = "exact_k", by_sequence: bool = False) -> str:
    rank = "row_number() OVER (ORDER BY {0} DESC, episode)" if ties == "exact_k" else "rank() OVER (ORDER BY {0} DESC)"
    return enumerated(ces, width, max_len, kinds, by_sequence) + f"SELECT episode, events, sets, utility, frequency, rank::INTEGER AS rank FROM (SELECT *, {rank.format(by)} AS rank FROM ep) WHERE rank <= {k}"


def threshold(ces: str, width: int, min_util: str, max_len: int | None = None) -> str:
    return enumerated(ces, width, max_len) + f"SELECT episode, events, sets, utility, frequency FROM ep WHERE utility >= {min_util}"


def windows(ces: str, width: int) -> str:
    """WITH clauses that end in w(ts, t, item, u, rest)."""
    return f"""
WITH ces AS ({ces}), s AS (SELECT DISTINCT t AS ts FROM ces),
w AS (SELECT ts, t, item, u, coalesce(sum(u) OVER (PARTITION BY ts ORDER BY t, item ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0)::BIGINT AS rest FROM s JOIN ces ON t >= ts AND t <= ts + {width})
"""


def one_episodes(ces: str, width: int) -> str:
    return windows(ces, width) + """, a AS (SELECT *, sum(u) OVER (PARTITION BY ts) AS everything FROM w)
SELECT item, count(*)::BIGINT AS frequency, sum(u)::BIGINT AS utility, sum(u + everything)::BIGINT AS raw, sum(everything)::BIGINT AS no_overlap, sum(u + rest)::BIGINT AS remaining FROM a WHERE t = ts GROUP BY item"""


def pair_occurrences(ces: str, width: int, first: str, second: str) -> str:
    """WITH clauses that end in o(ts, te, u): all occurrences of first>second; and m(ts, te, u): the minimal ones."""
    return f"""
WITH ces AS ({ces}), o AS (SELECT a.t AS ts, b.t AS te, a.u + b.u AS u FROM ces a JOIN ces b ON b.t > a.t AND b.t <= a.t + {width} WHERE a.item = '{first}' AND b.item = '{second}'),
e AS (SELECT ts, min(te) AS te, arg_min(u, te) AS u FROM o GROUP BY ts), m AS (SELECT ts, te, u FROM (SELECT *, lead(te) OVER (ORDER BY ts) AS nxt FROM e) WHERE nxt IS NULL OR nxt > te)
"""


def pairs(ces: str, width: int, kind: str) -> str:
    if kind == "simultaneous":
        return f"WITH ces AS ({ces}) SELECT a.item || '+' || b.item AS episode, sum(a.u + b.u)::BIGINT AS utility, count(*)::BIGINT AS frequency FROM ces a JOIN ces b ON a.t = b.t AND a.item < b.item GROUP BY 1"
    return f"""
WITH ces AS ({ces}), o AS (SELECT a.item AS x, b.item AS y, a.t AS ts, b.t AS te, a.u + b.u AS u FROM ces a JOIN (SELECT c.*, unnest(range(c.t - {width}, c.t)) AS s FROM ces c) b ON a.t = b.s),
e AS (SELECT x, y, ts, min(te) AS te, arg_min(u, te) AS u FROM o GROUP BY x, y, ts), m AS (SELECT *, lead(te) OVER (PARTITION BY x, y ORDER BY ts) AS nxt FROM e)
SELECT x || '>' || y AS episode, sum(u)::BIGINT AS utility, count(*)::BIGINT AS frequency FROM m WHERE nxt IS NULL OR nxt > te GROUP BY 1"""


def sets(ces: str) -> str:
    """WITH clauses that end in d(set_key, utility, n): different sets of two events or more."""
    return f"""
WITH ces AS ({ces}), b AS (SELECT t, string_agg(item, '+' ORDER BY item) AS set_key, sum(u) AS tu, count(*) AS events FROM ces GROUP BY t),
d AS (SELECT set_key, sum(tu)::BIGINT AS utility, count(*)::BIGINT AS n FROM b WHERE events > 1 GROUP BY set_key)
"""


def kth(values: str, k: int, short: str = "zero") -> str:
    """The kth largest of a column utility."""
    return f"SELECT {k}::INTEGER AS k, coalesce((SELECT CASE WHEN count(*) = {k} OR '{short}' = 'last' THEN min(utility) ELSE 0 END FROM (SELECT utility FROM ({values}) ORDER BY utility DESC LIMIT {k})), 0)::BIGINT AS min_util"
