"""Episode-parallel counting and the scan baselines, with their work counters."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.functions.automata import MachineBank, SlotBanks
from episodic.functions.carry import by_prefix, chain_starts, greedy, keep_prefixes
from episodic.functions.runs import scan_runs
from episodic.functions.store import level_store
from episodic.model import Episode, collect_episodes
from episodic.operators.segments import COUNTS_SQL, MOST_BROADCAST, arrays_of, needed, with_zeros

_COUNTS = pa.schema([("episode_id", pa.int64()), ("stream_key", pa.string()), ("support", pa.int64())])
COUNTERS = ("events_seen", "machine_steps", "probes", "pushes", "peak_list", "state_slots", "completions", "resets", "divergent_groups")


def _dealt(ev: DataFrame, eps: DataFrame, batch: int) -> tuple[DataFrame, dict[int, Episode], list[list[int]]]:
    """Each stream once for every group of `batch` candidates, with the events of the group's own symbols only."""
    episodes = collect_episodes(eps, MOST_BROADCAST)
    ids = sorted(episodes)
    groups = [ids[i : i + batch] for i in range(0, len(ids), batch)] or [[]]
    uses = sorted({(n, part) for part, group in enumerate(groups) for i in group for n in episodes[i].nodes})
    plan = ev.sparkSession.createDataFrame(uses, "sym string, part int")  # at most a row for each node of the candidates
    rows = needed(ev, episodes).select("stream_key", "sym", "t", "eid").join(plan, "sym")
    return rows, episodes, groups


def count_episode_parallel(ev: DataFrame, eps: DataFrame, kernel: str = "list", batch: int = 32) -> DataFrame:
    """(episode_id, support): every group of candidates scans each stream whole; parallel over candidates and streams only.

    kernel: "list" (exact automaton), "slot" (relaxed), "slot_scan" (the same, event by event, all machines of a size
    as arrays), or "latest" (exact, vectorised latest starts). A relaxed machine keeps one time a node, the newest, so
    its whole run is one lookup of the newest predecessor for each edge over all events at once.
    """
    rows, episodes, groups = _dealt(ev, eps, batch)
    machines = {"latest": _LatestScan, "slot": _LatestScan, "slot_scan": SlotBanks, "list": MachineBank}[kernel]

    class Scan:
        def __init__(self, key: tuple):
            self.stream, part = key
            own = {i: episodes[i] for i in groups[part]}
            self.bank = machines({i: e.relaxed for i, e in own.items()} if kernel == "slot" else own)

        def feed(self, table: pa.Table) -> None:
            if machines is _LatestScan:
                self.bank.feed(table)
            else:
                self.bank.feed(table.column("t").to_pylist(), table.column("sym").to_pylist())

        def rows(self) -> list[tuple]:
            return [(i, self.stream, n) for i, n in self.bank.counts.items()]

    return with_zeros(scan_runs(rows, ["stream_key", "part"], ["t", "eid"], Scan, COUNTS_SQL, _COUNTS), eps)


class _LatestScan:
    """Vectorised exact machines: each piece of the stream is counted with what the reach of the one before still covers.

    Between pieces a machine keeps its count and the position of its last accepted end. Pieces are at least as long as
    what is kept, so nothing is read more than twice; only an edge without an upper limit keeps the whole stream.
    """

    def __init__(self, episodes: dict[int, Episode]):
        self.listed = by_prefix([(i, e.nodes, tuple((x.low, x.high) for x in e.edges)) for i, e in episodes.items()])
        reaches = [e.reach for e in episodes.values()]
        self.reach = None if None in reaches else max(reaches, default=0)
        self.at = {i: (0, -(1 << 62), -(1 << 62)) for i in episodes}
        self.kept: pa.Table | None = None
        self.waiting: list[pa.Table] = []

    def feed(self, table: pa.Table) -> None:
        self.waiting.append(table.select(["sym", "t", "eid"]))
        if self.kept is None or sum(x.num_rows for x in self.waiting) >= self.kept.num_rows:
            self._count()

    @property
    def counts(self) -> dict[int, int]:
        if self.waiting:
            self._count()
        return {i: n for i, (n, _, _) in self.at.items()}

    def _count(self) -> None:
        whole = pa.concat_tables([self.kept, *self.waiting] if self.kept is not None else self.waiting)
        self.waiting = []
        events, memo = arrays_of(whole), {}
        for i, nodes, edges in self.listed:
            keep_prefixes(memo, nodes, edges)
            st, se, et, ee = chain_starts(events, nodes, edges, memo)
            n, t, e = self.at[i]
            first = int(np.searchsorted(st, t, "left"))
            while first < len(st) and (st[first], se[first]) <= (t, e):
                first += 1
            # an end that was passed over before starts no later than the last accepted end, so it is passed over again
            at = greedy(st[first:], se[first:], et[first:], ee[first:])
            if at:
                self.at[i] = (n + len(at), int(et[first + at[-1]]), int(ee[first + at[-1]]))
        if self.reach is None:
            self.kept = whole
        else:
            t = whole.column("t").to_numpy()
            self.kept = whole.slice(int(np.searchsorted(t, t[-1] - self.reach, "left")))


def multi_machine_scan(ev: DataFrame, eps: DataFrame, workers: int = 4, two_pass: bool = False, theta: int = 1) -> DataFrame:
    """The multicore baseline: each worker reads the stream once and advances all its machines through a symbol index.

    two_pass: slot machines first; only candidates that reach theta get a list machine. Those culled have support null.
    """
    n = eps.count()
    batch = max(1, math.ceil(n / workers))
    if not two_pass:
        return count_episode_parallel(ev, eps, "list", batch)
    upper = count_episode_parallel(ev, eps, "slot", batch).filter(F.col("support") >= theta).select("episode_id")
    left = level_store(eps.join(upper, "episode_id", "left_semi"), "scan-survivors")  # counted once, read twice
    exact = count_episode_parallel(ev, left, "list", batch)
    return eps.select("episode_id").join(exact, "episode_id", "left")


def counters(ev: DataFrame, eps: DataFrame, kernel: str = "list", group: int = 32) -> DataFrame:
    """One row of deterministic work counters of a kernel over all streams: the stand-in for profiler figures."""
    rows, episodes, groups = _dealt(ev, eps, 1 << 30)
    fields = [pa.field(c, pa.int64()) for c in COUNTERS]

    class Scan:
        def __init__(self, key: tuple):
            self.bank = MachineBank(episodes, kernel)

        def feed(self, table: pa.Table) -> None:
            self.bank.feed(table.column("t").to_pylist(), table.column("sym").to_pylist(), group)

        def rows(self) -> list[tuple]:
            self.bank.total()
            return [tuple(getattr(self.bank.work, c) for c in COUNTERS[:-1]) + (self.bank.divergent,)]

    each = scan_runs(rows, ["stream_key", "part"], ["t", "eid"], Scan, ", ".join(f"{c} bigint" for c in COUNTERS), pa.schema(fields))
    return each.agg(*[(F.max(c) if c == "peak_list" else F.sum(c)).alias(c) for c in COUNTERS])
