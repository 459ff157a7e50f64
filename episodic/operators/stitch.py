"""Segment-and-stitch counting as the method was first given: several start shifts a segment, neighbours joined.

For each segment and each shift k a machine starts the first k upper limits before the segment. It counts the
completions inside the segment, notes the first completion within reach of the segment's start and the completion that
crosses its end. Neighbours join where the left one's crossing equals the right one's first completion: the same event,
since at one time others may end too. The shifts do not always offer such a partner; then the result says so, and the
exact carry maps of operators.segments take over. With complete=True a segment also has a machine for every completion
within reach of its start that no shift begins with; whatever the left neighbour's crossing is, it then has a partner.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.functions.automata import ListAutomaton
from episodic.functions.carry import _next_free, by_time, chain_ends, chain_starts, earliest_ends
from episodic.functions.runs import over_runs
from episodic.functions.store import level_store
from episodic.model import Episode, collect_episodes
from episodic.operators.segments import MOST_BROADCAST, arrays_of, compose_maps, listed_by_prefix, map_steps, needed, place, with_zeros

#: First and crossing completion are (time, id); without one, the segment's own limit and NONE.
NONE = -(1 << 62)
TUPLES_SQL = "episode_id bigint, stream_key string, seg bigint, k int, a bigint, ae bigint, cnt bigint, b bigint, be bigint, own boolean"
_TUPLES = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("seg", pa.int64()), ("k", pa.int32()), *((c, pa.int64()) for c in ("a", "ae", "cnt", "b", "be")), ("own", pa.bool_())])
#: With carry maps: a row of its own for each, k -1.
MAPPED_SQL = f"{TUPLES_SQL}, steps array<bigint>"
_MAPPED = _TUPLES.append(pa.field("steps", pa.list_(pa.int64())))
#: Rounds of joins that a task does for a block of 2 ** ROUNDS segments.
ROUNDS = 6
_JOINED = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("last", pa.int64()), ("seg", pa.int64()), ("k", pa.int32()), *((c, pa.int64()) for c in ("a", "ae", "cnt", "b", "be"))])
JOINED_SQL = "episode_id bigint, stream_key string, last bigint, seg bigint, k int, a bigint, ae bigint, cnt bigint, b bigint, be bigint"


def machine_tuple(times: list[int], syms: list[str], e: Episode, lower: int, upper: int, k: int) -> tuple[int, int, int]:
    """(first completion, count, crossing completion) of shift k, one event at a time: the reference of machine_tuples."""
    reach = e.reach
    m = ListAutomaton(e)
    start = lower - sum(x.high for x in e.edges[:k])
    first, count, crossing = lower, 0, upper
    for t, s in zip(times, syms, strict=True):
        if t <= start:
            continue
        if t > upper + reach:
            break
        if not m.step(s, t):
            continue
        if t > upper:
            crossing = t
            break
        if t > lower:
            count += 1
            if first == lower and t <= lower + reach:
                first = t
    return first, count, crossing


def machine_tuples(events: dict[str, tuple[np.ndarray, np.ndarray]], e: Episode, lower: int, upper: int, complete: bool = False, ends: dict | None = None, memo: dict | None = None) -> list[tuple[int, int, int, int, int, int]]:
    """(k, first completion, its id, count, crossing completion, its id) of each shift k over the segment (lower, upper].

    A machine started at some time accepts the first latest start after it, and from there on what a greedy selection
    accepts; so all machines of a segment follow one list of next intervals, and paths that meet are walked once. No
    machine accepts any but the first interval of a start, so the list has only these. ends: by_time of events.
    """
    edges = tuple((x.low, x.high) for x in e.edges)
    if len(e.nodes) == 1:
        st, se, et, ee = chain_starts(events, e.nodes, edges)
    else:
        ends = {s: by_time(*x) for s, x in events.items()} if ends is None else ends
        st, se, et, ee = earliest_ends(*chain_ends(ends, e.nodes, edges, {} if memo is None else memo))
    n, hop = len(et), _next_free(st, se, et, ee).tolist()
    own, early, end, late = (int(np.searchsorted(et, x, "right")) for x in (lower, lower + e.reach, upper, upper + e.reach))
    begins = [int(np.searchsorted(st, lower - sum(x.high for x in e.edges[:k]), "right")) for k in range(len(e.nodes))]
    met: dict[int, tuple[int, int]] = {}  # interval past `lower`: completions in the segment from it on, and the crossing one

    def walk(i: int) -> tuple[int, int, int]:
        """(first interval past lower, completions, crossing interval) of a machine whose next interval is i."""
        while i < own:
            i = hop[i]
        path, at = [], i
        while at < end and at not in met:
            path.append(at)
            at = hop[at]
        c, z = met.get(at, (0, at))
        for j in reversed(path):
            c += 1
            met[j] = (c, z)
        return i, c, z

    out, firsts = [], set()
    for k, (i, c, z) in enumerate(map(walk, begins)):
        first = (int(et[i]), int(ee[i])) if i < min(early, end) else (lower, NONE)
        firsts.add(first)
        out.append((k, *first, c, *((int(et[z]), int(ee[z])) if z < min(late, n) else (upper, NONE))))
    if complete:
        for i in range(own, min(early, end)):
            first = (int(et[i]), int(ee[i]))
            if first not in firsts:
                firsts.add(first)
                _, c, z = walk(i)
                out.append((len(out), *first, c, *((int(et[z]), int(ee[z])) if z < min(late, n) else (upper, NONE))))
    return out


def segment_map(ev: DataFrame, eps: DataFrame, width: int, complete: bool = False, carry: bool = False) -> DataFrame:
    """(episode_id, stream_key, seg, k, a, ae, cnt, b, be, own) of each candidate, segment of the stream and shift; times of `seg` from its index.

    The map step of a segment reads its neighbours' events within the reach on both sides. Segments without any event
    in that range have no row; stitch() fills them in. own: the segment has events itself. carry: with a column `steps`
    and rows of k -1 that hold the exact carry maps, so that whoever needs them too reads the events once.
    """
    episodes = collect_episodes(eps, MOST_BROADCAST)
    reach = max((e.reach for e in episodes.values()), default=0)
    rows = place(needed(ev, episodes).select("stream_key", "sym", "t", "eid"), width, reach, both_sides=True)
    listed = listed_by_prefix(episodes)

    def kernel(table: pa.Table) -> list[tuple]:
        seg, stream = table.column("seg")[0].as_py(), table.column("stream_key")[0].as_py()
        events, lower, upper = arrays_of(table), seg * width, (seg + 1) * width
        ends, memo, out = {s: by_time(*x) for s, x in events.items()}, {}, []
        t = table.column("t").to_numpy()  # in order
        own = bool(np.searchsorted(t, lower, "right") < np.searchsorted(t, upper, "right"))
        more = (None,) if carry else ()
        for i, nodes, edges in listed:
            steps = map_steps(events, ends, nodes, edges, lower, memo, upper) if carry and nodes[-1] in events else []  # drops other prefixes
            if len(steps):
                out.append((i, stream, seg, -1, None, None, None, None, None, own, steps))
            out += [(i, stream, seg, *x, own, *more) for x in machine_tuples(events, episodes[i], lower, upper, complete, ends, memo if carry else {})]
        return out

    return over_runs(rows, ["stream_key", "seg"], ["t", "eid"], kernel, MAPPED_SQL if carry else TUPLES_SQL, _MAPPED if carry else _TUPLES)


def joined_pairs(rows: list[tuple], last: int, rounds: int) -> list[tuple[int, int, tuple]]:
    """(last, seg, tuple) after so many rounds of joins of neighbours; rows are (seg, k, a, ae, cnt, b, be)."""
    at: dict[int, list[tuple]] = {}
    for seg, *x in rows:
        at.setdefault(seg, []).append(tuple(x))
    for _ in range(rounds):
        up: dict[int, list[tuple]] = {}
        for seg, left in at.items():
            if seg % 2:
                continue
            if seg == last:  # no neighbour: up as it is; one whose neighbour lost all its tuples is not
                up[seg // 2] = left
                continue
            partner: dict[tuple, tuple] = {}  # machines with one first completion go on alike: one for each
            for _, a, ae, *to in at.get(seg + 1, ()):
                partner[a, ae] = min(partner.get((a, ae), tuple(to)), tuple(to))
            met = [(k, a, ae, cnt + (to := partner[b, be])[0], *to[1:]) for k, a, ae, cnt, b, be in left if (b, be) in partner]
            if met:
                up[seg // 2] = met
        at, last = up, last // 2
    return [(last, seg, x) for seg, xs in at.items() for x in xs]


def stitch(tuples: DataFrame, eps: DataFrame, width: int) -> DataFrame:
    """(episode_id, stream_key, cnt, matched, rounds): neighbours joined in ceil(log2 P) rounds, any P.

    cnt is null and matched false where some pair of neighbours has no partner for the tuple of the first segment.
    """
    span = tuples.filter("own").groupBy("stream_key").agg(F.min("seg").alias("lo"), F.max("seg").alias("hi"))
    most = span.agg(F.max(F.col("hi") - F.col("lo") + 1)).first()[0] or 0
    sizes = eps.select("episode_id", F.sequence(F.lit(0), F.size("nodes") - 1).alias("ks"))
    grid = span.select("stream_key", "lo", "hi", F.explode(F.sequence("lo", "hi")).alias("seg")).crossJoin(F.broadcast(sizes)).select("episode_id", "stream_key", "lo", "hi", "seg", F.explode("ks").alias("k"))
    edge, none = F.col("seg") * width, F.lit(NONE)
    # machines past the shifts are in the tuples only: the full join keeps them, and gives them their stream's limits
    both = grid.drop("lo", "hi").join(tuples, ["episode_id", "stream_key", "seg", "k"], "full_outer").join(span, "stream_key").filter("seg BETWEEN lo AND hi")
    full = both.select(
        "episode_id", "stream_key", (F.col("hi") - F.col("lo")).alias("last"), (F.col("seg") - F.col("lo")).alias("seg"), "k", F.coalesce("a", edge).alias("a"), F.coalesce("ae", none).alias("ae"),
        F.coalesce("cnt", F.lit(0)).alias("cnt"), F.coalesce("b", edge + width).alias("b"), F.coalesce("be", none).alias("be"),
    )
    rounds = max(0, int(most) - 1).bit_length()
    current = full
    for begun in range(0, rounds, ROUNDS):
        some = min(ROUNDS, rounds - begun)

        def kernel(table: pa.Table, some: int = some) -> list[tuple]:
            key = [table.column(c)[0].as_py() for c in ("episode_id", "stream_key")]
            rows = list(zip(*(table.column(c).to_pylist() for c in ("seg", "k", "a", "ae", "cnt", "b", "be")), strict=True))
            return [(*key, last, seg, *x) for last, seg, x in joined_pairs(rows, table.column("last")[0].as_py(), some)]

        blocks = current.withColumn("up", F.shiftright("seg", some))
        current = over_runs(blocks, ["episode_id", "stream_key", "up"], ["seg", "k"], kernel, JOINED_SQL, _JOINED)
    done = current.filter((F.col("k") == 0) & (F.col("seg") == 0)).select("episode_id", "stream_key", "cnt")
    every = span.select("stream_key").crossJoin(F.broadcast(eps.select("episode_id")))
    return every.join(done, ["episode_id", "stream_key"], "left").select("episode_id", "stream_key", "cnt", F.col("cnt").isNotNull().alias("matched"), F.lit(rounds).alias("rounds"))


def count_stitched(ev: DataFrame, eps: DataFrame, width: int, complete: bool = False) -> DataFrame:
    """(episode_id, support, matched): the stitched count, with exact carry maps where some segment pair did not match."""
    rows = level_store(segment_map(ev, eps, width, complete, carry=True), "map-tuples")  # read for the span, the joins and the maps
    tied = stitch(rows.filter("k >= 0").drop("steps"), eps, width)
    whole = level_store(tied.groupBy("episode_id").agg(F.sum("cnt").alias("cnt"), F.min("matched").alias("matched")), "stitched")
    missing = eps.join(whole.filter("matched"), "episode_id", "left_anti")
    maps = rows.filter("k = -1").select("episode_id", "stream_key", "seg", "steps").join(missing.select("episode_id"), "episode_id", "left_semi")
    exact = with_zeros(compose_maps(maps), missing).withColumnRenamed("support", "exact")
    joined = eps.select("episode_id").join(whole, "episode_id", "left").join(exact, "episode_id", "left")
    return joined.select("episode_id", F.when(F.col("matched"), F.col("cnt")).otherwise(F.col("exact")).cast("bigint").alias("support"), F.coalesce("matched", F.lit(False)).alias("matched"))
