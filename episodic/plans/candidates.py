"""Candidates of each size. Dropping the first or last node keeps every other delay, so support never grows with size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.model import EPISODES, Interval

CANDIDATE_BUDGET = 5_000_000


def symbol_table(ev: DataFrame) -> DataFrame:
    """(sym, support, first, last) of each symbol: its events, and the times of the first and last one."""
    return ev.groupBy("sym").agg(F.count("*").alias("support"), F.min("t").alias("first"), F.max("t").alias("last"))


def frequent_symbols(symbols: DataFrame, theta: int) -> DataFrame:
    """(nodes, low, high, support) of the symbols with at least theta events."""
    none = F.array().cast("array<bigint>")
    return symbols.filter(F.col("support") >= theta).select(F.array("sym").alias("nodes"), none.alias("low"), none.alias("high"), "support")


def level_one(ev: DataFrame, theta: int) -> DataFrame:
    """(nodes, low, high, support) of the symbols with at least theta events."""
    return frequent_symbols(symbol_table(ev), theta)


def _shared(first: int, n: int):
    """n nodes from the first-th on and the limits between them, as one string."""
    return F.to_json(F.struct(F.slice("nodes", first, n).alias("n"), F.slice("low", first, n - 1).alias("l"), F.transform(F.slice("high", first, n - 1), lambda h: F.coalesce(h, F.lit(-1))).alias("h")))


def count_candidates(frequent: DataFrame, intervals: list[Interval], k: int, n: int) -> int:
    """How many candidates of size k the n frequent ones of size k - 1 give, known before any of them is made."""
    if k == 2:
        return n * n * len(intervals)
    ends = frequent.groupBy(_shared(2, k - 2).alias("shared")).agg(F.count("*").alias("x"))
    starts = frequent.groupBy(_shared(1, k - 2).alias("shared")).agg(F.count("*").alias("y"))
    return ends.join(starts, "shared").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0))).first()[0]


def next_candidates(frequent: DataFrame, intervals: list[Interval], k: int) -> DataFrame:
    """(nodes, low, high, bound) of size k from the frequent ones of size k - 1; bound: the smaller of the two supports.

    k = 2: all ordered pairs of frequent symbols times the intervals. k >= 3: two episodes that agree on all but the
    first node of one and the last of the other, an equality join on the shared part.
    """
    if k == 2:
        limits = F.explode(F.array(*[F.struct(F.lit(i.low).cast("bigint").alias("lo"), F.lit(i.high).cast("bigint").alias("hi")) for i in intervals]))
        a = frequent.select(F.col("nodes").alias("na"), F.col("support").alias("sa"))
        b = frequent.select(F.col("nodes").alias("nb"), F.col("support").alias("sb"))
        # frequent symbols squared is the candidate set itself, within the budget
        pairs = a.crossJoin(b).withColumn("i", limits)
        return pairs.select(F.concat("na", "nb").alias("nodes"), F.array("i.lo").alias("low"), F.array("i.hi").alias("high"), F.least("sa", "sb").alias("bound"))
    left = frequent.select("nodes", "low", "high", F.col("support").alias("sa"), _shared(2, k - 2).alias("shared"))
    right = frequent.select(F.element_at("nodes", -1).alias("node"), F.element_at("low", -1).alias("lo"), F.element_at("high", -1).alias("hi"), F.col("support").alias("sb"), _shared(1, k - 2).alias("shared"))
    return left.join(right, "shared").select(F.concat("nodes", F.array("node")).alias("nodes"), F.concat("low", F.array("lo")).alias("low"), F.concat("high", F.array("hi")).alias("high"), F.least("sa", "sb").alias("bound"))


def numbered(candidates: DataFrame) -> DataFrame:
    """With an episode_id in the order of nodes and limits: a range sort, so that no task numbers all; write it before use."""
    return candidates.orderBy("nodes", "low", "high").withColumn("episode_id", F.monotonically_increasing_id())


def as_table(candidates: DataFrame) -> DataFrame:
    return candidates.select(*[f.name for f in EPISODES])
