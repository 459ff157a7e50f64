"""The SQL surface: functions and table functions on episodes in their written form."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from episodic.functions.automata import ListAutomaton
from episodic.functions.carry import chain_starts, greedy
from episodic.model import Episode, Interval, format_episode, parse_episode

PARSED = T.StructType([T.StructField("nodes", T.ArrayType(T.StringType())), T.StructField("low", T.ArrayType(T.LongType())), T.StructField("high", T.ArrayType(T.LongType()))])


@F.pandas_udf(PARSED)
def parse_udf(texts: pd.Series) -> pd.DataFrame:
    es = [parse_episode(t) for t in texts]
    return pd.DataFrame({"nodes": [list(e.nodes) for e in es], "low": [[x.low for x in e.edges] for e in es], "high": [[x.high for x in e.edges] for e in es]})


@F.pandas_udf(T.StringType())
def canonical_udf(texts: pd.Series) -> pd.Series:
    return texts.map(lambda t: format_episode(parse_episode(t)))


@F.pandas_udf(T.LongType())
def episode_count(sym: pd.Series, t: pd.Series, episode: pd.Series) -> int:
    """Grouped aggregate for small groups: the support of one episode in the group's events.

    Only times order the events, so an occurrence starts strictly after the end of the one before, whatever order
    simultaneous rows arrive in.
    """
    e = parse_episode(episode.iloc[0])
    events = {}
    for s in set(e.nodes):
        own = np.sort(t[sym == s].to_numpy(np.int64))
        events[s] = (own, np.zeros(len(own), np.int64))
    return len(greedy(*chain_starts(events, e.nodes, tuple((x.low, x.high) for x in e.edges))))


def _udtf():
    @F.udtf(returnType="episode string, support bigint, ends array<bigint>")
    class EpisodeOccurrences:
        """TABLE(stream_key, sym, t, eid) PARTITION BY stream_key ORDER BY t, eid, and an episode: its support and ends.

        The machine steps as rows arrive: only its lists and the ends found are held, never the partition.
        """

        def __init__(self):
            self.machine, self.episode, self.ends = None, "", []

        def eval(self, row, episode: str) -> Iterator[tuple]:
            if self.machine is None:
                self.machine, self.episode = ListAutomaton(parse_episode(episode)), episode
            if self.machine.step(row["sym"], row["t"]):
                self.ends.append(row["t"])
            return
            yield

        def terminate(self) -> Iterator[tuple]:
            if self.machine is not None:
                yield self.episode, len(self.ends), self.ends

    return EpisodeOccurrences


def _mining_udtf():
    @F.udtf(returnType="size int, episode string, support bigint")
    class MineEpisodes:
        """TABLE(stream_key, sym, t, eid) PARTITION BY stream_key ORDER BY t, eid, intervals as `low-high,low-high`, theta
        and most nodes: every frequent episode of the stream. For streams that fit one worker; mine() has no such limit."""

        def __init__(self):
            self.events: dict[str, tuple[list[int], list[int]]] = {}
            self.asked = None

        def eval(self, row, intervals: str, theta: int, max_nodes: int) -> Iterator[tuple]:
            self.asked = (intervals, theta, max_nodes)
            t, e = self.events.setdefault(row["sym"], ([], []))
            t.append(row["t"])
            e.append(row["eid"])
            return
            yield

        def terminate(self) -> Iterator[tuple]:
            if self.asked is None:
                return
            text, theta, most = self.asked
            limits = [tuple(map(int, x.split("-"))) for x in text.split(",")]
            events = {s: (np.array(t, np.int64), np.array(e, np.int64)) for s, (t, e) in self.events.items()}
            level = [((s,), ()) for s, (t, _) in events.items() if len(t) >= theta]
            symbols = [nodes[0] for nodes, _ in level]
            memo: dict = {}
            for size in range(1, most + 1):
                held = set()
                for nodes, edges in level:
                    n = len(greedy(*chain_starts(events, nodes, edges, memo)))
                    if n >= theta:
                        held.add((nodes, edges))
                        yield size, format_episode(Episode(nodes, tuple(Interval(*x) for x in edges))), n
                # a longer episode is frequent only if what it is without its first node is
                level = [((*nodes, s), (*edges, i)) for nodes, edges in held for s in symbols for i in limits if size == 1 or ((*nodes[1:], s), (*edges[1:], i)) in held]

    return MineEpisodes


def _maps_udtf():
    @F.udtf(returnType="episode_id bigint, stream_key string, seg bigint, steps array<bigint>")
    class EpisodeMaps:
        """A row of operators.segments.placed_segments, written episodes (one a line, of two and more nodes) and the width
        of segments: the carry map of each episode that can end in the segment; episode_id is its line, from 0."""

        def __init__(self):
            self.text, self.listed = None, []

        def eval(self, stream_key: str, seg: int, events: bytes, episodes: str, width: int) -> Iterator[tuple]:
            from episodic.operators.segments import listed_by_prefix, map_steps, unpacked

            if episodes != self.text:
                self.text, self.listed = episodes, listed_by_prefix(dict(enumerate(map(parse_episode, episodes.split("\n")))))
            ends, memo = unpacked(bytes(events)), {}
            for k, nodes, edges in self.listed:
                if nodes[-1] in ends and len(steps := map_steps({}, ends, nodes, edges, seg * width, memo)):
                    yield k, stream_key, seg, steps.tolist()

    return EpisodeMaps


def register(spark: SparkSession) -> None:
    """parse_episode, canonical_episode, episode_count, and the table functions episode_occurrences, mine_episodes and episode_maps, by name."""
    spark.udf.register("parse_episode", parse_udf)
    spark.udf.register("canonical_episode", canonical_udf)
    spark.udf.register("episode_count", episode_count)
    spark.udtf.register("episode_occurrences", _udtf())
    spark.udtf.register("mine_episodes", _mining_udtf())
    spark.udtf.register("episode_maps", _maps_udtf())
