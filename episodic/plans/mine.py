"""Level-wise mining: candidates of a size, the relaxed cull, the exact count, and on to the next size."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.functions.store import level_store
from episodic.model import Interval
from episodic.operators.chains import shape
from episodic.operators.scans import count_episode_parallel
from episodic.operators.segments import count_nonoverlapped, count_placed, placed_segments, segment_width
from episodic.operators.stitch import count_stitched
from episodic.plans.candidates import CANDIDATE_BUDGET, as_table, count_candidates, frequent_symbols, next_candidates, numbered, symbol_table
from episodic.plans.dispatch import CrossoverModel, choose_counting
from episodic.plans.relax import upper_counts

FREQUENT_SQL = "size int, nodes array<string>, low array<bigint>, high array<bigint>, support bigint"
#: Frequent symbols that may be broadcast to filter the events.
MOST_SYMBOLS = 1_000_000
#: Events that "auto" lets groups of candidates read, each group the whole stream; beyond it the stream is cut into segments.
MOST_COPIES = 1_000_000


@dataclass
class Level:
    """What one size cost: its candidates, those the free bound and the relaxed pass removed, and the frequent ones."""

    size: int
    candidates: int
    survivors: int
    frequent: int
    counting: str
    seconds: float


@dataclass
class Mined:
    frequent: DataFrame
    report: list[Level] = field(default_factory=list)


def mine(
    ev: DataFrame, intervals: list[Interval], theta: int, max_nodes: int = 8, strategy: str = "auto", counting: str = "auto", engine: str = "arrow", kernel: str = "latest", width: int | None = None,
    model: CrossoverModel | None = None, batch: int = 32, budget: int = CANDIDATE_BUDGET, uniform: bool = False, stitching: str = "carry", membership_only: bool = False,
) -> Mined:
    """All episodes of up to max_nodes nodes whose edges take intervals from `intervals` and whose support reaches theta.

    strategy: "two_pass" culls by relaxed counts first, "one_pass" counts all exactly; "auto" takes two passes where the
    relaxed machine is cheaper than the exact one (list automata) and one where both cost the same (latest starts). counting: "segment", "episode"
    or "auto" (the dispatcher, up to MOST_COPIES). stitching: how segments are put together, by "carry" maps or, "faithful", by joining the
    shifted machines of neighbours, with carry maps where none match. uniform: one interval for all edges of an episode.
    membership_only: supports may be any bound that reaches theta; a candidate whose relaxed form has every lower limit
    0 already is then not counted twice. A level with more candidates than `budget` is refused with its number before
    any is made. Levels are written to the shared folder, and so are the events once they are cut into segments, which
    all counts by carry maps then read as they are; the driver holds counters only.
    """
    if theta < 1 or max_nodes < 1 or not intervals:
        raise ValueError("theta and max_nodes are at least 1, and there is at least one interval")
    if strategy not in ("auto", "two_pass", "one_pass") or counting not in ("auto", "segment", "episode"):
        raise ValueError("strategy is auto, two_pass or one_pass; counting is auto, segment or episode")
    if stitching not in ("carry", "faithful"):
        raise ValueError("stitching is carry or faithful")
    slots = ev.sparkSession.sparkContext.defaultParallelism

    def count(e: DataFrame, c: DataFrame, way: str, relaxed: bool = False) -> DataFrame:
        if way == "episode":  # the relaxed form has a cheaper machine
            listed = kernel == "list" and not relaxed
            # enough groups to fill the slots: each reads the stream once, which costs less than a few list machines
            share = max(1 if listed else batch, math.ceil(c.count() / (2 * slots)))
            return count_episode_parallel(e, c, "slot" if relaxed and kernel == "list" else kernel, share)
        if stitching == "faithful":
            reach = shape(c)[1]
            if reach is None:
                raise ValueError("faithful stitching needs an upper limit on every edge")
            return count_stitched(e, c, max(width or segment_width(spread, reach, slots), reach + 1)).select("episode_id", "support")
        if engine == "arrow" and longest is not None:
            rows, wide, parts = segments(k)
            return count_placed(rows, c, wide, parts)
        return count_nonoverlapped(e, c, engine, width, spread=spread)

    def segments(k: int) -> tuple[DataFrame, int, int]:
        """(the events in segments, their width, how many) for episodes of k nodes, and of some more: longer reaches make wider segments."""
        if k > placed.get("nodes", 0):
            most = min(max_nodes, max(4, 2 * k))
            reach = (most - 1) * longest
            wide = max(width or segment_width(spread, reach, slots), reach + 1)
            rows = level_store(placed_segments(ev, wide, reach), f"segments-{most}")
            placed.update(nodes=most, rows=rows, width=wide, parts=(spread[1] - spread[0]) // wide + 2)
        return placed["rows"], placed["width"], placed["parts"]

    def chosen(m: int, k: int) -> str:
        if counting != "auto":
            return counting
        way = choose_counting(m, k, slots, batch, model)
        groups = math.ceil(m / max(batch, math.ceil(m / (2 * slots))))
        return "segment" if spread[2] * groups > MOST_COPIES and all(i.high is not None for i in intervals) else way

    began = time.time()
    longest = None if any(i.high is None for i in intervals) else max(i.high for i in intervals)
    placed: dict = {}
    alphabet = level_store(symbol_table(ev), "symbols")  # one scan gives the alphabet, its counts and the extent
    symbols, *spread = alphabet.agg(F.count("*"), F.min("first"), F.max("last"), F.coalesce(F.sum("support"), F.lit(0))).first()
    frequent = level_store(frequent_symbols(alphabet, theta), "1")
    n = frequent.count()
    report = [Level(1, symbols, symbols, n, "scan", time.time() - began)]
    levels = [frequent.select(F.lit(1).alias("size"), "nodes", "low", "high", "support")]
    kept = frequent.select(F.col("nodes")[0].alias("sym"))
    ev = ev.join(F.broadcast(kept) if n <= MOST_SYMBOLS else kept, "sym", "left_semi").select("stream_key", "sym", "t", "eid")
    for k in range(2, max_nodes + 1):
        if not n:
            break
        began = time.time()
        m = count_candidates(frequent, intervals, k, n)
        if m > budget:
            raise ValueError(f"{m} candidates of size {k} from {n} frequent ones; the budget is {budget}: raise theta")
        found = next_candidates(frequent, intervals, k)
        if uniform:
            found = found.filter((F.size(F.array_distinct("low")) == 1) & (F.size(F.array_distinct("high")) == 1))
        cands = level_store(numbered(found), f"candidates-{k}")
        if uniform:
            m = cands.count()
        if not m:
            break
        way = chosen(m, k)
        table = as_table(cands)
        left, sure = m, None
        if strategy == "two_pass" or (strategy == "auto" and way == "episode" and kernel == "list"):
            upper = upper_counts(ev, table, lambda e, c, w=way: count(e, c, w, True))
            table = level_store(table.join(upper.filter(F.col("upper") >= theta), "episode_id"), f"survivors-{k}")
            if membership_only:
                loose = F.forall("low", lambda x: x == 0)
                sure = table.filter(loose).select("episode_id", F.col("upper").alias("support"))
                table = table.filter(~loose)
            table = table.drop("upper")
            left = table.count()
        way = chosen(left, k)
        exact = count(ev, table, way).filter(F.col("support") >= theta)
        exact = exact if sure is None else exact.unionByName(sure)
        frequent = level_store(as_table(cands).join(exact, "episode_id").select("nodes", "low", "high", "support"), str(k))
        n = frequent.count()
        report.append(Level(k, m, left, n, way, time.time() - began))
        levels.append(frequent.select(F.lit(k).alias("size"), "nodes", "low", "high", "support"))
    return Mined(reduce(DataFrame.unionByName, levels), report)


def top_k_episodes(frequent: DataFrame, k: int) -> DataFrame:
    """The k best-supported episodes of each size; ties by the episode itself."""
    from pyspark.sql import Window

    w = Window.partitionBy("size").orderBy(F.desc("support"), "nodes", "low", "high")
    return frequent.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def culling(report: list[Level]) -> list[tuple[int, int, int, float]]:
    """(size, candidates, removed, share removed) of each level that had a relaxed pass."""
    return [(r.size, r.candidates, r.candidates - r.survivors, (r.candidates - r.survivors) / r.candidates) for r in report if r.size > 1]
