"""The relaxed pass: upper bounds with every lower limit 0, and the cull that they allow."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from episodic.functions.store import level_store
from episodic.operators.segments import count_nonoverlapped

Counter = Callable[[DataFrame, DataFrame], DataFrame]


def relaxed_forms(eps: DataFrame) -> DataFrame:
    """(episode_id, relaxed_id, nodes, low, high): candidates that differ in lower limits only share a relaxed form."""
    form = eps.groupBy("nodes", "high").agg(F.min("episode_id").alias("relaxed_id"), F.collect_list("episode_id").alias("members"))
    return form.select("relaxed_id", "nodes", F.transform("high", lambda h: F.lit(0).cast("bigint")).alias("low"), "high", F.explode("members").alias("episode_id"))


def upper_counts(ev: DataFrame, eps: DataFrame, counter: Counter = count_nonoverlapped) -> DataFrame:
    """(episode_id, upper): the count of the relaxed form, never below the exact count."""
    forms = relaxed_forms(eps)
    distinct = forms.select(F.col("relaxed_id").alias("episode_id"), "nodes", "low", "high").dropDuplicates(["episode_id"])
    upper = counter(ev, distinct).select(F.col("episode_id").alias("relaxed_id"), F.col("support").alias("upper"))
    return forms.select("episode_id", "relaxed_id").join(upper, "relaxed_id").select("episode_id", "upper")


def count_two_pass(ev: DataFrame, eps: DataFrame, theta: int, counter: Counter = count_nonoverlapped) -> DataFrame:
    """(episode_id, upper, survived, exact): the relaxed pass on all, the exact pass on those that reach theta; exact null if culled."""
    upper = level_store(upper_counts(ev, eps, counter), "upper")  # read by the cull and by the result
    left = eps.join(upper.filter(F.col("upper") >= theta).select("episode_id"), "episode_id", "left_semi")
    exact = counter(ev, left).withColumnRenamed("support", "exact")
    return upper.join(exact, "episode_id", "left").select("episode_id", "upper", (F.col("upper") >= theta).alias("survived"), "exact")


def count_one_pass(ev: DataFrame, eps: DataFrame, theta: int, counter: Counter = count_nonoverlapped) -> DataFrame:
    """(episode_id, support) of the candidates that reach theta, by the exact pass alone."""
    return counter(ev, eps).filter(F.col("support") >= theta)
