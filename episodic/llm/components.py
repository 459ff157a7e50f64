"""Connected components of large edge tables by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import materialize


def _mark(edges: DataFrame) -> tuple[int, str]:
    n, h = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return n, str(h)


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) of every node that an edge names; component is the smallest node reachable.

    Each round hangs every node under the smallest neighbour it knows: first its larger neighbours (large star), then
    its smaller ones (small star). The minima are hash aggregates that combine before the shuffle, written before the
    join so that adaptive execution can split a node with very many edges. Rounds are written to the shared folder;
    the loop ends when a round changes nothing.
    """
    own = edges.filter(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    current = materialize(own, "edges")
    before = _mark(current)
    while before[0]:
        both = current.unionByName(current.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = materialize(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "least")
        large = both.filter("v > u").join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = materialize(large.distinct(), "edges")
        least = materialize(large.groupBy("u").agg(F.min("v").alias("m")), "least")
        hung = large.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        current = materialize(hung.unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "edges")
        after = _mark(current)
        if after == before:
            break
        before = after
    roots = current.groupBy("v").agg(F.lit(1).alias("one")).select(F.col("v").alias("node"), F.col("v").alias("component"))
    return current.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
