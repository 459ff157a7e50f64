"""Slices of a recording mined in turn, what changes between them, and the summary graph."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from episodic.model import Interval
from episodic.operators.segments import count_nonoverlapped
from episodic.plans.mine import Mined, mine


def slice_events(ev: DataFrame, width: int, origin: int = 0) -> DataFrame:
    """ev with its slice number in the stream key: each slice is a stream of its own, counted from scratch."""
    return ev.withColumn("slice", F.floor((F.col("t") - origin) / width).cast("bigint")).withColumn("stream_key", F.concat_ws("/", "stream_key", F.col("slice").cast("string")))


def slice_supports(ev: DataFrame, eps: DataFrame, width: int, origin: int = 0) -> DataFrame:
    """(episode_id, slice, support) of fixed episodes in each slice where they occur: all slices in one job."""
    counts = count_nonoverlapped(slice_events(ev, width, origin).drop("slice"), eps, by_stream=True)
    return counts.groupBy("episode_id", F.element_at(F.split("stream_key", "/"), -1).cast("bigint").alias("slice")).agg(F.sum("support").alias("support"))


def mine_partitions(ev: DataFrame, slices: list[tuple[int, int]], intervals: list[Interval], theta: int, **options) -> list[tuple[int, Mined, float]]:
    """(slice number, result, seconds over slice duration) of consecutive slices [from, to), mined one after the other.

    A ratio of at most 1 (times in microseconds) means that mining keeps up with the recording.
    """
    out = []
    for i, (lo, hi) in enumerate(slices):
        began = time.time()
        m = mine(ev.filter((F.col("t") >= lo) & (F.col("t") < hi)), intervals, theta, **options)
        out.append((i, m, (time.time() - began) / max(1e-9, (hi - lo) / 1e6)))
    return out


def union_slices(mined: list[tuple[int, Mined, float]]) -> DataFrame:
    return reduce(DataFrame.unionByName, [m.frequent.withColumn("slice", F.lit(i).cast("bigint")) for i, m, _ in mined])


def track_evolution(results: DataFrame, by: list[str]) -> DataFrame:
    """by + (slice, before, after, change, delta) between consecutive slices; results has by + (slice, support), a row where frequent.

    change: appears, persists or vanishes. The slices are those from the first to the last of the table.
    """
    ahead = results.select(*by, (F.col("slice") + 1).alias("slice"), F.col("support").alias("before"))
    here = results.select(*by, "slice", F.col("support").alias("after"))
    span = results.agg(F.min("slice").alias("lo"), F.max("slice").alias("hi"))
    both = ahead.join(here, [*by, "slice"], "full_outer").join(F.broadcast(span), (F.col("slice") > F.col("lo")) & (F.col("slice") <= F.col("hi")))
    kind = F.when(F.col("before").isNull(), "appears").when(F.col("after").isNull(), "vanishes").otherwise("persists")
    return both.select(*by, "slice", "before", "after", kind.alias("change"), (F.coalesce("after", F.lit(0)) - F.coalesce("before", F.lit(0))).alias("delta"))


def connection_graph(frequent: DataFrame) -> DataFrame:
    """(src, dst, low, high, support, episodes): every edge of the frequent episodes, with the best support that shows it."""
    edges = frequent.filter(F.size("nodes") > 1).select("support", F.posexplode(F.slice("nodes", 1, F.size("nodes") - 1)).alias("i", "src"), "nodes", "low", "high")
    each = edges.select("src", F.expr("nodes[i + 1]").alias("dst"), F.expr("low[i]").alias("low"), F.expr("high[i]").alias("high"), "support")
    return each.groupBy("src", "dst", "low", "high").agg(F.max("support").alias("support"), F.count("*").alias("episodes"))


def connection_matrix(frequent: DataFrame, symbols: list[str]) -> DataFrame:
    """src by dst: the best support of any edge between them, 0 where there is none."""
    best = connection_graph(frequent).groupBy("src").pivot("dst", symbols).agg(F.max("support"))
    return best.na.fill(0, symbols)


def contrast(supports: DataFrame, group: str, a, b) -> DataFrame:
    """(episode_id, a, b, difference): supports of two groups of streams; supports has (episode_id, group, support)."""
    side = lambda v: F.coalesce(F.sum(F.when(F.col(group) == v, F.col("support"))), F.lit(0)).cast("bigint")
    return supports.groupBy("episode_id").agg(side(a).alias("a"), side(b).alias("b")).withColumn("difference", F.col("a") - F.col("b"))


def gaps(ev: DataFrame) -> DataFrame:
    """(stream_key, t, gap): each event's distance from the one before it in its stream."""
    w = Window.partitionBy("stream_key").orderBy("t", "eid")
    return ev.select("stream_key", "t", (F.col("t") - F.lag("t").over(w)).alias("gap"))


def bursts(ev: DataFrame, silence: int) -> DataFrame:
    """(stream_key, start, end, n): runs of events without a gap of `silence` or more."""
    at = F.timestamp_micros("t")
    w = F.session_window(at, f"{silence} microseconds")
    return ev.groupBy("stream_key", w).agg(F.min("t").alias("start"), F.max("t").alias("end"), F.count("*").alias("n")).select("stream_key", "start", "end", "n")
