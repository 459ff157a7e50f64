"""SQL builders for the oracle queries: the same measures in plain SQL, run by another engine on the same tables."""

from __future__ import annotations

from episodic.model import Episode, format_episode

EVENTS = {
    "types": "SELECT 'all' AS stream_key, event_type AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "users": "SELECT CAST(user_id AS VARCHAR) AS stream_key, event_type AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "user26": "SELECT 'all' AS stream_key, 'u' || (user_id % 26) AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "slices": "SELECT CAST((dayofmonth(ts) - 1) // 10 AS VARCHAR) AS stream_key, 'u' || (user_id % 60) AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "type_slices": "SELECT CAST((dayofmonth(ts) - 1) // 10 AS VARCHAR) AS stream_key, event_type AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "days": "SELECT CAST(epoch_us(ts) // 86400000000 AS VARCHAR) AS stream_key, event_type AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "json": "SELECT 'all' AS stream_key, 'k' || (CAST(json_extract_string(props, '$.k') AS INT) % 26) AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "values": "SELECT 'all' AS stream_key, event_type || ':' || least(3, CAST(floor(value / 50.0) AS BIGINT)) AS sym, epoch_us(ts) AS t, event_id AS eid FROM events",
    "orders": "SELECT CAST(o_custkey AS VARCHAR) AS stream_key, o_orderpriority AS sym, epoch_us(o_orderdate) AS t, o_orderkey AS eid FROM orders",
    "flags": "SELECT CAST(l_suppkey AS VARCHAR) AS stream_key, l_returnflag || l_linestatus AS sym, epoch_us(l_shipdate) AS t, CAST(0 AS BIGINT) AS eid FROM lineitem",
    "brands": "SELECT CAST(l_suppkey AS VARCHAR) AS stream_key, p_brand AS sym, epoch_us(l_shipdate) AS t, CAST(0 AS BIGINT) AS eid FROM lineitem JOIN part ON l_partkey = p_partkey",
    "regions": "SELECT 'all' AS stream_key, r_name AS sym, epoch_us(o_orderdate) AS t, o_orderkey AS eid FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "roles": "SELECT CAST(conv_id AS VARCHAR) AS stream_key, role AS sym, turn * 1000000 AS t, turn AS eid FROM conversations",
    "words": "SELECT CAST(doc_id AS VARCHAR) AS stream_key, w AS sym, (i - 1) * 1000000 AS t, i - 1 AS eid FROM (SELECT doc_id, unnest(ws) AS w, generate_subscripts(ws, 1) AS i FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]+') AS ws FROM documents))",
    "tags": "SELECT CAST(page_id AS VARCHAR) AS stream_key, w AS sym, (i - 1) * 1000000 AS t, i - 1 AS eid FROM (SELECT page_id, unnest(ws) AS w, generate_subscripts(ws, 1) AS i FROM (SELECT page_id, regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1) AS ws FROM pages))",
    "labels": "SELECT 'all' AS stream_key, 'l' || label AS sym, vec_id * 1000000 AS t, vec_id AS eid FROM embeddings",
}


def _values(episodes: list[Episode], n: int) -> str:
    rows = []
    for i, e in enumerate(episodes):
        if len(e.nodes) == n:
            cells = [str(i), f"'{format_episode(e)}'", *(f"'{x}'" for x in e.nodes), *(f"CAST({v} AS BIGINT)" for x in e.edges for v in (x.low, 1 << 61 if x.high is None else x.high))]
            rows.append("(" + ", ".join(cells) + ")")
    names = ["ep", "episode", *(f"n{k}" for k in range(1, n + 1)), *(f"{c}{k}" for k in range(1, n) for c in "lh")]
    return f"(VALUES {', '.join(rows)}) AS v({', '.join(names)})"


def chains(source: str, episodes: list[Episode], asof: bool = False) -> str:
    """CTEs ev, eps, iv: iv(ep, stream_key, st, se, et, ee) is the latest-start table of all episodes.

    The newest start is the maximum over all predecessors in the interval; with asof the newest predecessor alone.
    """
    sizes = sorted({len(e.nodes) for e in episodes})
    parts = [f"ev AS MATERIALIZED ({EVENTS.get(source, source)})"]
    parts.append("eps AS (" + " UNION ALL ".join(f"SELECT ep, episode FROM {_values(episodes, n)}" for n in sizes) + ")")
    finals = []
    for n in sizes:
        parts.append(f"e{n} AS (SELECT * FROM {_values(episodes, n)})")
        parts.append(f"c{n}_1 AS (SELECT ep, stream_key, t AS et, eid AS ee, t AS st, eid AS se FROM ev JOIN e{n} ON sym = n1)")
        for k in range(2, n + 1):
            own = f"(SELECT ep, stream_key, t, eid, l{k - 1} AS l, h{k - 1} AS h, t - l{k - 1} AS s FROM ev JOIN e{n} ON sym = n{k})"
            if asof:
                best = f"(SELECT ep, stream_key, et, max({{'st': st, 'se': se}}) AS m FROM c{n}_{k - 1} GROUP BY ALL)"
                body = f"SELECT a.ep, a.stream_key, a.t AS et, a.eid AS ee, b.m.st AS st, b.m.se AS se FROM {own} a ASOF JOIN {best} b ON a.ep = b.ep AND a.stream_key = b.stream_key AND a.s > b.et WHERE a.t - b.et <= a.h"
            else:
                body = f"SELECT a.ep, a.stream_key, a.t AS et, a.eid AS ee, max({{'st': b.st, 'se': b.se}}) AS m FROM {own} a JOIN c{n}_{k - 1} b ON a.ep = b.ep AND a.stream_key = b.stream_key AND a.t - b.et > a.l AND a.t - b.et <= a.h GROUP BY ALL"
                body = f"SELECT ep, stream_key, et, ee, m.st AS st, m.se AS se FROM ({body})"
            parts.append(f"c{n}_{k} AS ({body})")
        finals.append(f"SELECT ep, stream_key, st, se, et, ee FROM c{n}_{n}")
    parts.append("iv AS (" + " UNION ALL ".join(finals) + ")")
    return ", ".join(parts)


_ITEM = "{'st': st, 'se': se, 'et': et, 'ee': ee, 'c': CAST(0 AS BIGINT)}"
_ZERO = "{'st': CAST(-1 AS BIGINT), 'se': CAST(-1 AS BIGINT), 'et': CAST(-4611686018427387904 AS BIGINT), 'ee': CAST(-4611686018427387904 AS BIGINT), 'c': CAST(0 AS BIGINT)}"
_STEP = "CASE WHEN b.st > a.et OR (b.st = a.et AND b.se > a.ee) THEN {'st': b.st, 'se': b.se, 'et': b.et, 'ee': b.ee, 'c': a.c + 1} ELSE a END"


def fold(iv: str = "iv", by: str = "ep, stream_key") -> str:
    """The greedy choice of intervals by end, as a fold over each group's sorted list: (by, support)."""
    return f"SELECT {by}, list_reduce(list_prepend({_ZERO}, list({_ITEM} ORDER BY et, ee)), lambda a, b: {_STEP}).c AS support FROM {iv} GROUP BY {by}"


def support_sql(source: str, episodes: list[Episode], asof: bool = False) -> str:
    """(episode, support) summed over streams, 0 where there is none."""
    return f"WITH {chains(source, episodes, asof)}, g AS ({fold()}) SELECT eps.episode, CAST(coalesce(sum(support), 0) AS BIGINT) AS support FROM eps LEFT JOIN g USING (ep) GROUP BY eps.episode"


def stream_support_sql(source: str, episodes: list[Episode], asof: bool = False) -> str:
    """(episode, stream_key, support) where there is any."""
    return f"WITH {chains(source, episodes, asof)}, g AS ({fold()}) SELECT episode, stream_key, support FROM g JOIN eps USING (ep)"


def intervals_sql(source: str, episodes: list[Episode]) -> str:
    """CTEs up to picked(ep, stream_key, rank, st, et): the chosen intervals, stepping to the next end in a recursion."""
    return f"""RECURSIVE {chains(source, episodes)},
      nxt AS (SELECT ep, stream_key, st, se, et, ee, row_number() OVER (PARTITION BY ep, stream_key ORDER BY et, ee) AS i FROM iv),
      picked AS (
        SELECT ep, stream_key, i, CAST(1 AS BIGINT) AS rank, st, et, ee FROM nxt WHERE i = 1
        UNION ALL
        SELECT ep, stream_key, m.i, rank + 1, m.st, m.et, m.ee FROM (
          SELECT p.ep, p.stream_key, p.rank, min({{'i': n.i, 'st': n.st, 'et': n.et, 'ee': n.ee}}) AS m FROM picked p JOIN nxt n
            ON n.ep = p.ep AND n.stream_key = p.stream_key AND (n.st > p.et OR (n.st = p.et AND n.se > p.ee)) GROUP BY p.ep, p.stream_key, p.rank))"""
