"""Level-wise mining from SQL: each level is one statement that calls the table function episode_maps on every segment."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.functions import sql as surface
from episodic.functions.store import level_store
from episodic.model import Interval, collect_episodes, episode_table, format_episode
from episodic.operators.segments import MOST_BROADCAST, compose_maps, placed_segments, segment_width, with_zeros
from episodic.plans.candidates import CANDIDATE_BUDGET, as_table, count_candidates, frequent_symbols, next_candidates, numbered, symbol_table


def mine_by_table_function(ev: DataFrame, intervals: list[Interval], theta: int, max_nodes: int, width: int | None = None) -> DataFrame:
    """(size, nodes, low, high, support) of all frequent episodes; supports are sums over streams, as in mine().

    The events are written once, cut into segments. A call of the table function holds one segment and the tables of one
    candidate, so no stream is one worker. Intervals have upper limits here.
    """
    if theta < 1 or max_nodes < 1 or not intervals or any(i.high is None for i in intervals):
        raise ValueError("theta and max_nodes are at least 1, and there is at least one interval, each with an upper limit")
    spark = ev.sparkSession
    surface.register(spark)
    alphabet = level_store(symbol_table(ev), "symbols")
    lo, hi, events = alphabet.agg(F.min("first"), F.max("last"), F.coalesce(F.sum("support"), F.lit(0))).first()
    frequent = level_store(frequent_symbols(alphabet, theta), "1")
    levels = [frequent.select(F.lit(1).alias("size"), "nodes", "low", "high", "support")]
    n = frequent.count()
    if n and max_nodes > 1:
        reach = (max_nodes - 1) * max(i.high for i in intervals)
        width = max(width or segment_width((lo, hi, events), reach, spark.sparkContext.defaultParallelism), reach + 1)
        kept = ev.join(frequent.select(F.col("nodes")[0].alias("sym")), "sym", "left_semi")
        level_store(placed_segments(kept, width, reach), "segments").createOrReplaceTempView("episode_segments")
    for k in range(2, max_nodes + 1):
        m = count_candidates(frequent, intervals, k, n) if n else 0
        if not m:
            break
        if m > CANDIDATE_BUDGET:
            raise ValueError(f"{m} candidates of size {k}; the budget is {CANDIDATE_BUDGET}: raise theta")
        cands = level_store(numbered(next_candidates(frequent, intervals, k)), f"candidates-{k}")
        episodes = list(collect_episodes(as_table(cands), MOST_BROADCAST).values())
        eps = episode_table(spark, episodes)
        maps = spark.sql(
            "SELECT m.* FROM episode_segments s, LATERAL episode_maps(s.stream_key, s.seg, s.events, :candidates, :width) m",
            args={"candidates": "\n".join(map(format_episode, episodes)), "width": width},
        )
        counts = with_zeros(compose_maps(maps, (hi - lo) // width + 2), eps).filter(F.col("support") >= theta)
        frequent = level_store(eps.join(counts, "episode_id").select("nodes", "low", "high", "support"), str(k))
        n = frequent.count()
        levels.append(frequent.select(F.lit(k).alias("size"), "nodes", "low", "high", "support"))
    return reduce(DataFrame.unionByName, levels)
