"""Latest-start tables: the relational core of exact counting.

For each event that can end an episode the table holds the latest start of a valid chain that ends there. It grows by
one node a step, as an as-of join: an event takes the newest predecessor that is more than `low` older, and keeps it if
it isn't more than `high` older. That one predecessor decides, because latest starts never fall with the end. Shifting
predecessors by `low` turns the pair of limits into one order, so every interval shares one sort.

Candidates with a common prefix share its rows. Rows are keyed by (prefix, stream, time bucket); a predecessor is also
copied to the next bucket where its reach ends, so a single endless stream still spreads over many tasks. An edge without
an upper limit reaches over all buckets: there each bucket hands its newest chain on, one row a prefix and bucket.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def prefix_key(k: int) -> Column:
    """The first k nodes of an episode, and the limits between them, as one string."""
    return F.to_json(F.struct(F.slice("nodes", 1, k).alias("n"), F.slice("low", 1, k - 1).alias("l"), F.transform(F.slice("high", 1, k - 1), lambda h: F.coalesce(h, F.lit(-1))).alias("h")))


def prefix_plan(eps: DataFrame, k: int) -> DataFrame:
    """(prefix, parent, sym, low, high) of the distinct prefixes of k nodes."""
    at = eps.filter(F.size("nodes") >= k)
    if k == 1:
        return at.select(prefix_key(1).alias("prefix"), F.col("nodes")[0].alias("sym")).distinct()
    return at.select(prefix_key(k).alias("prefix"), prefix_key(k - 1).alias("parent"), F.col("nodes")[k - 1].alias("sym"), F.col("low")[k - 2].alias("low"), F.col("high")[k - 2].alias("high")).distinct()


def first_nodes(ev: DataFrame, plan: DataFrame) -> DataFrame:
    """The table of one-node prefixes: each event starts and ends its own chain."""
    return ev.join(plan, "sym").select("prefix", "stream_key", F.col("t").alias("st"), F.col("eid").alias("se"), F.col("t").alias("et"), F.col("eid").alias("ee"))


def _handed_on(before: DataFrame, after: DataFrame) -> DataFrame:
    """For open edges, the newest chain before each bucket as one more predecessor of it; buckets are few, rows are not."""
    keys = ["prefix", "stream_key", "bucket"]
    newest = before.filter("high IS NULL").groupBy(*keys, "low").agg(F.max(F.struct("s", "chain")).alias("n"))
    asked = after.filter("high IS NULL").select(*keys, "low").distinct()
    both = newest.join(asked, [*keys, "low"], "full_outer")
    w = Window.partitionBy("prefix", "stream_key").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = both.withColumn("n", F.last("n", ignorenulls=True).over(w)).filter("n IS NOT NULL")
    return carried.select("prefix", "stream_key", F.col("n.s").alias("s"), F.lit(1).alias("kind"), F.col("n.chain.t").alias("t"), F.lit(None).cast("bigint").alias("eid"), "low", F.lit(None).cast("bigint").alias("high"), F.col("n.chain").alias("chain"), "bucket")


def extend(table: DataFrame, ev: DataFrame, plan: DataFrame, bucket: int, open_edges: bool = False) -> DataFrame:
    """The table of the longer prefixes in plan. bucket: width of time buckets, at least the widest high - low."""
    before = table.join(plan.withColumnRenamed("prefix", "longer"), table["prefix"] == plan["parent"]).select(
        F.col("longer").alias("prefix"), "stream_key", (F.col("et") + F.col("low")).alias("s"), F.lit(1).alias("kind"), F.col("et").alias("t"), F.lit(None).cast("bigint").alias("eid"), "low", "high",
        F.struct(F.col("et").alias("t"), "st", "se").alias("chain"),
    )
    after = ev.join(plan.drop("parent"), "sym").select(
        "prefix", "stream_key", F.col("t").alias("s"), F.lit(0).alias("kind"), "t", "eid", "low", "high", F.lit(None).cast(before.schema["chain"].dataType).alias("chain")
    )
    b = F.floor(F.col("s") / bucket)
    far = F.floor((F.col("s") + F.coalesce(F.col("high"), F.col("low")) - F.col("low")) / bucket)
    before, after = before.withColumn("bucket", F.explode(F.array_distinct(F.array(b, far)))), after.withColumn("bucket", b)
    rows = before.unionByName(after)
    if open_edges:
        rows = rows.unionByName(_handed_on(before, after))
    w = Window.partitionBy("prefix", "stream_key", "bucket").orderBy("s", "kind", F.col("chain.st"), F.col("chain.se")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    newest = rows.withColumn("newest", F.last("chain", ignorenulls=True).over(w))
    held = newest.filter((F.col("kind") == 0) & F.col("newest").isNotNull() & (F.col("high").isNull() | (F.col("t") - F.col("newest.t") <= F.col("high"))))
    return held.select("prefix", "stream_key", F.col("newest.st").alias("st"), F.col("newest.se").alias("se"), F.col("t").alias("et"), F.col("eid").alias("ee"))


def shape(eps: DataFrame) -> tuple[int, int | None, int]:
    """(most nodes, longest reach, least bucket width) of a candidate table; reach None if an edge has no upper limit."""
    reach = F.when(F.exists("high", lambda h: h.isNull()), F.lit(None)).otherwise(F.aggregate("high", F.lit(0).cast("bigint"), lambda a, h: a + h))
    span = F.coalesce(F.array_max(F.zip_with("high", "low", lambda h, x: F.coalesce(h, x) - x)), F.lit(1))
    r = eps.agg(F.max(F.size("nodes")), F.max(reach), F.sum(reach.isNull().cast("int")), F.max(span)).first()
    if r[0] is None:
        return 0, 0, 1
    return r[0], (None if r[2] else r[1] or 0), max(1, r[3] or 1)


def latest_starts(ev: DataFrame, eps: DataFrame, bucket: int | None = None) -> DataFrame:
    """(episode_id, stream_key, st, se, et, ee): for each possible end of each episode the latest start.

    bucket: width of time buckets in the unit of t; by default 64 times the widest interval, and with an open edge a
    1,024th of the time that the events span, if that is more. Episodes of different sizes may be mixed; an episode of
    one node has every event of its symbol as an occurrence.
    """
    nodes, reach, least = shape(eps)
    if not bucket and reach is None:
        lo, hi = ev.agg(F.min("t"), F.max("t")).first()
        bucket = ((hi or 0) - (lo or 0)) // 1_024 + 1
        bucket = max(bucket, 64 * least if least > 1 else 1)
    bucket = max(bucket or 64 * least, least)
    ev = ev.select("stream_key", "sym", "t", "eid")
    table, out = None, []
    for k in range(1, nodes + 1):
        plan = prefix_plan(eps, k)
        table = first_nodes(ev, plan) if k == 1 else extend(table, ev, plan, bucket, reach is None)
        whole = eps.filter(F.size("nodes") == k).select("episode_id", prefix_key(k).alias("prefix"))
        out.append(table.join(whole, "prefix").select("episode_id", "stream_key", "st", "se", "et", "ee"))
    if not out:
        empty = ev.join(eps.select("episode_id"), F.lit(False))
        return empty.select("episode_id", "stream_key", F.col("t").alias("st"), F.col("eid").alias("se"), F.col("t").alias("et"), F.col("eid").alias("ee"))
    return reduce(DataFrame.unionByName, out)
