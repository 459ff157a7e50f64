"""Intervals, episodes and how they are written."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: Candidate table: one row for each episode. `high` null: no upper limit on that edge.
EPISODES = T.StructType([
    T.StructField("episode_id", T.LongType(), False),
    T.StructField("nodes", T.ArrayType(T.StringType(), False), False),
    T.StructField("low", T.ArrayType(T.LongType(), False), False),
    T.StructField("high", T.ArrayType(T.LongType(), True), False),
])


@dataclass(frozen=True, order=True)
class Interval:
    """A delay interval: open below, closed above, in microseconds; high None means no upper limit."""

    low: int
    high: int | None

    def __post_init__(self):
        if self.low < 0 or (self.high is not None and self.high <= self.low):
            raise ValueError(f"need 0 <= low < high, got ({self.low}, {self.high}]")


@dataclass(frozen=True)
class Episode:
    """A serial episode: nodes and, between each two, the interval that their delay must fall in."""

    nodes: tuple[str, ...]
    edges: tuple[Interval, ...] = ()

    def __post_init__(self):
        if not self.nodes or len(self.edges) != len(self.nodes) - 1:
            raise ValueError("an episode of N nodes has N - 1 intervals, N >= 1")

    @property
    def reach(self) -> int | None:
        """The longest time from first to last node; None if an edge has no upper limit."""
        return None if any(e.high is None for e in self.edges) else sum(e.high for e in self.edges)

    @property
    def relaxed(self) -> Episode:
        """The same nodes and upper limits with every lower limit 0; its count bounds this one's from above."""
        return Episode(self.nodes, tuple(Interval(0, e.high) for e in self.edges))


_EDGE = re.compile(r"-\((\d+),(\d+|inf)\]->")


def format_episode(e: Episode) -> str:
    """`A-(5,10]->B`: delays in whole units, inf for no upper limit."""
    out = e.nodes[0]
    for edge, node in zip(e.edges, e.nodes[1:], strict=True):
        out += f"-({edge.low},{'inf' if edge.high is None else edge.high}]->{node}"
    return out


def parse_episode(text: str) -> Episode:
    parts = _EDGE.split(text.strip())
    nodes = tuple(p.strip() for p in parts[::3])
    if any(not n for n in nodes):
        raise ValueError(f"not an episode: {text!r}")
    edges = tuple(Interval(int(a), None if b == "inf" else int(b)) for a, b in zip(parts[1::3], parts[2::3], strict=True))
    return Episode(nodes, edges)


def episode_table(spark: SparkSession, episodes: list[Episode]) -> DataFrame:
    """A candidate table; ids are places in the list."""
    rows = [(i, list(e.nodes), [x.low for x in e.edges], [x.high for x in e.edges]) for i, e in enumerate(episodes)]
    return spark.createDataFrame(rows, EPISODES)


def collect_episodes(eps: DataFrame, most: int) -> dict[int, Episode]:
    """The candidates by id, for broadcast; refuses more than `most`."""
    rows = eps.select("episode_id", "nodes", "low", "high").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"over {most} candidates: raise the threshold, or count in batches")
    return {r["episode_id"]: Episode(tuple(r["nodes"]), tuple(Interval(a, b) for a, b in zip(r["low"], r["high"], strict=True))) for r in rows}


def pairs_of(symbols: list[str], intervals: list[Interval]) -> list[Episode]:
    """All two-node episodes over the symbols and intervals."""
    return [Episode((a, b), (i,)) for a in symbols for b in symbols for i in intervals]
