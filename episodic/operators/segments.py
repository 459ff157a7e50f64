"""Counting by time segments with exact carry maps: the engine's default.

The stream is cut into segments (lower, upper]. One shuffle brings each segment its own events and, from its left
neighbour, those within the longest reach. A task finds the latest starts of all candidates in its segment and writes
one small carry map for each; maps of neighbouring segments compose, in rounds of FAN, to the count. Parallel over
segments, streams and candidate groups; no segment needs more memory than its events.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.functions.carry import apply_map, apply_steps, by_prefix, by_time, carry_steps, chain_ends, compose_steps, earliest_ends, greedy, keep_prefixes
from episodic.functions.runs import fold_lists, fold_rows, in_batches, over_runs
from episodic.model import Episode, collect_episodes
from episodic.operators.chains import latest_starts, shape

#: Events of a segment aimed at, maps composed in one step, and candidates that may be sent to every task.
SEGMENT_EVENTS, FAN, MOST_BROADCAST = 200_000, 64, 1_000_000

_MAPS = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("seg", pa.int64()), ("steps", pa.list_(pa.int64()))])
MAPS_SQL = "episode_id bigint, stream_key string, seg bigint, steps array<bigint>"
_COUNTS = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("support", pa.int64())])
COUNTS_SQL = "episode_id bigint, stream_key string, support bigint"


def extent(ev: DataFrame) -> tuple[int | None, int | None, int]:
    """(first time, last time, events)."""
    return tuple(ev.agg(F.min("t"), F.max("t"), F.count("*")).first())


def segment_width(extent_: tuple[int | None, int | None, int], reach: int, slots: int) -> int:
    """A width over the reach that gives about SEGMENT_EVENTS events a segment, and not fewer segments than slots if that allows."""
    lo, hi, n = extent_
    span = max(1, (hi or 0) - (lo or 0) + 1)
    parts = max(1, min(math.ceil(n / SEGMENT_EVENTS), span), min(slots, n // 2_000))
    return max(4 * reach + 1, math.ceil(span / parts))


def place(ev: DataFrame, width: int, reach: int, both_sides: bool = False) -> DataFrame:
    """ev with the segment `seg` = (seg * width, (seg + 1) * width] of each row, copied to the neighbours that need it.

    An event goes to the next segment if it is within reach of its start, and, with both_sides, to the one before too.
    """
    if width <= reach:
        raise ValueError(f"a segment must be longer than the reach: {width} <= {reach}")
    seg = F.floor((F.col("t") - 1) / width).cast("bigint")
    right = F.when(F.col("t") > (seg + 1) * width - reach, seg + 1)
    left = F.when(F.col("t") <= seg * width + reach, seg - 1) if both_sides else F.lit(None).cast("bigint")
    return ev.withColumn("seg", F.explode(F.array_compact(F.array(seg, right, left))))


def arrays_of(table: pa.Table) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Times and ids by symbol of a run sorted by (t, eid)."""
    syms = table.column("sym").combine_chunks().dictionary_encode()
    code = syms.indices.to_numpy()
    t, e = table.column("t").to_numpy(), table.column("eid").to_numpy()
    order = np.argsort(code, kind="stable")
    cut = np.searchsorted(code[order], np.arange(len(syms.dictionary) + 1))
    return {s: (t[order[a:b]], e[order[a:b]]) for s, a, b in zip(syms.dictionary.to_pylist(), cut[:-1], cut[1:], strict=True)}


def needed(ev: DataFrame, episodes: dict[int, Episode]) -> DataFrame:
    """Only the events that some candidate uses; the filter reaches the scan."""
    syms = sorted({n for e in episodes.values() for n in e.nodes})
    return ev.filter(F.col("sym").isin(syms)) if len(syms) <= 1_000 else ev


def map_steps(events: dict, ends: dict, nodes: tuple[str, ...], edges: tuple, bound: int, memo: dict, upper: int | None = None) -> np.ndarray:
    """The flat carry map of one candidate in the segment (bound, upper], empty if it can't end there; ends: by_time of events."""
    if len(nodes) == 1:
        t, e = events[nodes[0]]
        starts = (t, e, t, e)
    else:
        keep_prefixes(memo, nodes, edges)
        starts = chain_ends(ends, nodes, edges, memo)
    a, b = int(np.searchsorted(starts[2], bound, "right")), None if upper is None else int(np.searchsorted(starts[2], upper, "right"))
    own = earliest_ends(*(x[a:b] for x in starts))
    return carry_steps(*own, bound).ravel()


def listed_by_prefix(episodes: dict[int, Episode]) -> list[tuple]:
    """(id, nodes, edges): a group shares prefixes, and a task holds those of one candidate at a time."""
    return by_prefix([(k, e.nodes, tuple((x.low, x.high) for x in e.edges)) for k, e in episodes.items()])


def segment_maps(ev: DataFrame, episodes: dict[int, Episode], width: int, groups: int = 1) -> DataFrame:
    """(episode_id, stream_key, seg, steps): a carry map for each candidate in each segment where it can end."""
    reach = max((e.reach for e in episodes.values()), default=0)
    rows = place(needed(ev, episodes).select("stream_key", "sym", "t", "eid"), width, reach)
    rows = rows.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))) if groups > 1 else rows.withColumn("part", F.lit(0))
    listed = listed_by_prefix(episodes)
    share = math.ceil(len(listed) / groups) if listed else 1

    def kernel(table: pa.Table) -> Iterator[tuple]:
        part, seg, stream = (table.column(c)[0].as_py() for c in ("part", "seg", "stream_key"))
        events, memo = arrays_of(table), {}
        ends = {s: by_time(*x) for s, x in events.items()}
        each = ((k, map_steps(events, ends, nodes, edges, seg * width, memo)) for k, nodes, edges in listed[part * share : (part + 1) * share] if nodes[-1] in events)
        return ((k, stream, seg, steps) for k, steps in each if len(steps))

    return over_runs(rows, ["stream_key", "seg", "part"], ["t", "eid"], kernel, MAPS_SQL, _MAPS, 2_000)


_PLACED = pa.schema([("stream_key", pa.string()), ("seg", pa.int64()), ("events", pa.binary())])
PLACED_SQL = "stream_key string, seg bigint, events binary"
_ENDS = pa.schema([("sym", pa.string()), *((c, pa.list_(pa.int64())) for c in ("t", "first", "last"))])


def placed_segments(ev: DataFrame, width: int, reach: int) -> DataFrame:
    """(stream_key, seg, events): one row for each segment with its events and those within reach of its start.

    events: for each symbol what by_time gives, packed. Whoever counts often writes this once; each count then reads it
    without a shuffle or a sort. Enough for episodes of two and more nodes within the reach.
    """
    rows = place(ev.select("stream_key", "sym", "t", "eid"), width, reach)

    def kernel(table: pa.Table) -> list[tuple]:
        ends = {s: by_time(*x) for s, x in arrays_of(table).items()}
        arrays = [pa.array([x[i] for x in ends.values()], _ENDS.field(1).type) for i in range(3)]
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, _ENDS) as out:
            out.write_batch(pa.RecordBatch.from_arrays([pa.array(list(ends), pa.string()), *arrays], schema=_ENDS))
        return [(table.column("stream_key")[0].as_py(), table.column("seg")[0].as_py(), sink.getvalue().to_pybytes())]

    return over_runs(rows, ["stream_key", "seg"], ["t", "eid"], kernel, PLACED_SQL, _PLACED, 1)


def unpacked(events: bytes) -> dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """What by_time gave for each symbol, from a row of placed_segments."""
    table = pa.ipc.open_stream(events).read_all().combine_chunks()
    lists = [table.column(c).chunk(0) for c in ("t", "first", "last")] if table.num_rows else []
    return {s: tuple(x.values.to_numpy()[x.offsets[i].as_py() : x.offsets[i + 1].as_py()] for x in lists) for i, s in enumerate(table.column("sym").to_pylist())}


def count_placed(placed: DataFrame, eps: DataFrame, width: int, segments: int) -> DataFrame:
    """(episode_id, support) of candidates of two and more nodes over placed_segments of that width."""
    episodes = collect_episodes(eps, MOST_BROADCAST)
    slots = placed.sparkSession.sparkContext.defaultParallelism
    listed = listed_by_prefix(episodes)
    groups = max(1, min(-(-slots // max(1, segments)), len(listed) // 500))
    share = math.ceil(len(listed) / groups) if listed else 1
    rows = placed.select("*", F.lit(0).alias("part"))
    if groups > 1:
        rows = placed.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))).repartition("stream_key", "seg", "part")

    def maps(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for b in batches:
            for i in range(b.num_rows):
                stream, seg, events, part = (b.column(c)[i].as_py() for c in ("stream_key", "seg", "events", "part"))
                ends, memo = unpacked(events), {}
                for k, nodes, edges in listed[part * share : (part + 1) * share]:
                    if nodes[-1] in ends and len(steps := map_steps({}, ends, nodes, edges, seg * width, memo)):
                        yield k, stream, seg, steps

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from in_batches(maps(batches), _MAPS, 2_000)

    return with_zeros(compose_maps(rows.mapInArrow(run, MAPS_SQL), segments), eps)


def _steps(flat: list[int]) -> list[tuple]:
    return [tuple(flat[i : i + 5]) for i in range(0, len(flat), 5)]


def carry_maps(intervals: DataFrame, width: int) -> DataFrame:
    """The same maps from a relational latest-start table (operators.chains)."""

    def kernel(table: pa.Table) -> list[tuple]:
        k, stream, s = (table.column(c)[0].as_py() for c in ("episode_id", "stream_key", "seg"))
        st, se, et, ee = (table.column(c).to_numpy() for c in ("st", "se", "et", "ee"))
        return [(k, stream, s, carry_steps(st, se, et, ee, s * width).ravel())]

    cut = intervals.withColumn("seg", _segment_of("et", width))
    return over_runs(cut, ["episode_id", "stream_key", "seg"], ["et", "ee"], kernel, MAPS_SQL, _MAPS)


def _segment_of(t: str, width: int):
    return F.floor((F.col(t) - 1) / width).cast("bigint")


_CHOSEN = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("rank", pa.int64()), ("st", pa.int64()), ("et", pa.int64())])
_STATES = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("seg", pa.list_(pa.int64())), ("n", pa.list_(pa.int64())), ("t", pa.list_(pa.int64())), ("e", pa.list_(pa.int64()))])
STATES_SQL = "episode_id bigint, stream_key string, seg array<bigint>, n array<bigint>, t array<bigint>, e array<bigint>"


def chosen_intervals(intervals: DataFrame, width: int) -> DataFrame:
    """(episode_id, stream_key, rank, st, et): what the greedy selection accepts from a latest-start table.

    The carry maps of a stream's segments, a few numbers each, are walked in order to the state in which the selection
    enters each segment; then every segment selects for itself, so no stream is one task.
    """

    def entered(key: tuple, rows: list[tuple]) -> tuple:
        n, t, e, out = 0, -(1 << 62), -(1 << 62), []
        for seg, flat in rows:
            out.append((seg, n, t, e))
            c, t, e = apply_map(_steps(flat), t, e)
            n += c
        return (*key, *map(list, zip(*out, strict=True)))

    def kernel(table: pa.Table) -> list[tuple]:
        k, stream, n, t, e = (table.column(c)[0].as_py() for c in ("episode_id", "stream_key", "n", "t", "e"))
        st, se, et, ee = (table.column(c).to_numpy() for c in ("st", "se", "et", "ee"))
        first = int(np.searchsorted(st, t, "left"))
        while first < len(st) and (st[first], se[first]) <= (t, e):
            first += 1
        at = greedy(st[first:], se[first:], et[first:], ee[first:])
        return [(k, stream, n + i + 1, int(st[first + j]), int(et[first + j])) for i, j in enumerate(at)]

    states = fold_rows(carry_maps(intervals, width), ["episode_id", "stream_key"], ["seg"], entered, STATES_SQL, _STATES)
    each = states.select("episode_id", "stream_key", F.explode(F.arrays_zip("seg", "n", "t", "e")).alias("x")).select("episode_id", "stream_key", "x.seg", "x.n", "x.t", "x.e")
    cut = intervals.withColumn("seg", _segment_of("et", width)).join(each, ["episode_id", "stream_key", "seg"])
    return over_runs(cut, ["episode_id", "stream_key", "seg"], ["et", "ee"], kernel, "episode_id bigint, stream_key string, rank bigint, st bigint, et bigint", _CHOSEN)


def compose_maps(maps: DataFrame, segments: int | None = None) -> DataFrame:
    """(episode_id, stream_key, support): neighbouring maps composed in rounds, then applied to an empty past."""
    if segments is None:
        lo, hi = maps.agg(F.min("seg"), F.max("seg")).first()
        segments = 0 if lo is None else hi - lo + 1

    def nothing() -> np.ndarray:
        return np.zeros((0, 5), np.int64)

    def joined(whole: np.ndarray, flat: np.ndarray) -> np.ndarray:
        return compose_steps(whole, flat.reshape(-1, 5))

    def past() -> tuple:
        return 0, -(1 << 62), -(1 << 62)

    def applied(state: tuple, flat: np.ndarray) -> tuple:
        n, t, e = state
        c, t, e = apply_steps(flat.reshape(-1, 5), t, e)
        return n + c, t, e

    while segments > FAN:
        up = maps.select("episode_id", "stream_key", F.floor(F.col("seg") / FAN).cast("bigint").alias("up"), "seg", "steps")
        maps = fold_lists(up, ["episode_id", "stream_key", "up"], ["seg"], "steps", nothing, joined, lambda key, whole: (*key, whole.ravel()), MAPS_SQL, _MAPS)
        segments = segments // FAN + 2
    return fold_lists(maps, ["episode_id", "stream_key"], ["seg"], "steps", past, applied, lambda key, state: (*key, state[0]), COUNTS_SQL, _COUNTS)


def with_zeros(counts: DataFrame, eps: DataFrame) -> DataFrame:
    """(episode_id, support) of every candidate, summed over streams; 0 where it never occurs."""
    total = counts.groupBy("episode_id").agg(F.sum("support").alias("support"))
    return eps.select("episode_id").join(total, "episode_id", "left").select("episode_id", F.coalesce("support", F.lit(0)).cast("bigint").alias("support"))


def count_nonoverlapped(ev: DataFrame, eps: DataFrame, engine: str = "arrow", width: int | None = None, groups: int | None = None, by_stream: bool = False, spread: tuple | None = None) -> DataFrame:
    """Exact support of each candidate: the largest number of pairwise non-overlapped occurrences.

    engine "arrow": candidates go to every task (MOST_BROADCAST at most), events are shuffled once. "relational": the
    latest-start table by windows, for candidate tables of any size and for edges without an upper limit. Both then use
    carry maps. With by_stream the rows
    are (episode_id, stream_key, support) without zeros. spread: what extent(ev) gave, or gave for a stream that holds
    ev, so that a caller with many counts reads it once.
    """
    if engine not in ("arrow", "relational"):
        raise ValueError("engine is arrow or relational")
    slots = ev.sparkSession.sparkContext.defaultParallelism
    spread = spread or extent(ev)
    if engine == "arrow":
        episodes = collect_episodes(eps, MOST_BROADCAST)
        reaches = [e.reach for e in episodes.values()]
        reach = None if any(r is None for r in reaches) else max(reaches, default=0)
    else:
        _, reach, _ = shape(eps)
    if engine == "arrow" and not groups:
        # segments that the events need fill the slots first; what is left is filled by groups of candidates, since a
        # candidate costs a few fixed steps in every segment, and a group a copy of the events
        groups = max(1, min(-(-slots // max(1, math.ceil(spread[2] / SEGMENT_EVENTS))), len(episodes) // 500))
    width = max(width or segment_width(spread, reach or 0, -(-slots // (groups or 1))), (reach or 0) + 1)
    if engine == "arrow" and reach is not None:
        maps = segment_maps(ev, episodes, width, groups)
    else:  # open edges reach over every segment: buckets hand chains on, and only the relational form does that
        maps = carry_maps(latest_starts(ev, eps), width)
    segments = 1 if spread[0] is None else (spread[1] - spread[0]) // width + 2
    counts = compose_maps(maps, segments)
    return counts if by_stream else with_zeros(counts, eps)


def count_independent(ev: DataFrame, eps: DataFrame, width: int) -> DataFrame:
    """The contrast: each segment counts on its own and counts are added up. Occurrences across a cut are lost."""
    own = ev.select(F.concat_ws("/", "stream_key", _segment_of("t", width).cast("string")).alias("stream_key"), "sym", "t", "eid")
    return with_zeros(count_nonoverlapped(own, eps, width=width, by_stream=True), eps)
