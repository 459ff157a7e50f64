"""Sharding by sampled splitters.

Keys are drawn into a sample with a chance in proportion to their size; quantiles of the sample are the splitters of
many fine ranges, which all records then fall into. The exact rows and bytes of each range are counted; a range that
turns out fuller than OVERFULL times what was aimed at is subdivided at quantiles of its own keys and counted again,
until none is. Then a range is cut at exact places inside it where a shard ends. The shard of a record follows from the
bytes before it in key order, so shards differ by less than one record, whatever the sample was; the sample only
decides how even the work is.

The key is a hash of the text followed by one of the id: equal texts lie side by side, and a text that a third of all
rows hold is still cut where ranges need it. Only slim rows (id, size, checksum, key) move, never a text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .runtime import materialize

#: Keys in the sample at most, in expectation, and bytes-weighted ranges a shard at least.
SAMPLE_KEYS, RANGES_A_SHARD = 20_000, 16
#: Rows of a range aimed at, and ranges at most: what the driver holds is bounded by these.
RANGE_ROWS, MOST_RANGES = 200_000, 8_192
#: A range of more than so many times the rows aimed at is subdivided, in so many rounds at most (keys may all be one).
OVERFULL, ROUNDS = 2, 8


def _slim(docs: DataFrame, key: str, text: str) -> DataFrame:
    size = F.coalesce(F.octet_length(text), F.lit(0)).cast("bigint") + 8
    body = F.coalesce(F.col(text), F.lit(""))
    order = F.shiftright(F.xxhash64(body), 1).bitwiseAND(F.lit(~0x7FFFFF)).bitwiseOR(F.pmod(F.xxhash64(key), F.lit(1 << 23)))
    return docs.select(F.col(key).alias("k"), size.alias("size"), F.crc32(F.encode(body, "utf-8")).alias("text_crc32"), order.alias("order"), F.xxhash64(key, F.lit("draw")).alias("draw"))


def splitters(slim: DataFrame, total: int, n: int, sample_keys: int = SAMPLE_KEYS) -> list[int]:
    """n - 1 quantiles, at most, of a sample in which a record's chance grows with its size; about sample_keys records."""
    rate = sample_keys / max(total, 1)
    chance = F.least(F.lit(1.0), F.col("size") * F.lit(rate))
    drawn = slim.filter((F.pmod("draw", F.lit(1 << 40)) / F.lit(float(1 << 40))) < chance)
    got = drawn.select("order", F.greatest(F.lit(1.0), F.col("size") * F.lit(rate)).alias("w")).collect()
    got = sorted((r["order"], r["w"]) for r in got)
    whole, run, out = sum(w for _, w in got), 0.0, []
    for k, w in got:
        run += w
        if run * n / whole >= len(out) + 1 and len(out) < n - 1 and (not out or k > out[-1]):
            out.append(k)
    return out


def _placed(cuts: list[int]):
    at = np.array(cuts, np.int64)

    @F.arrow_udf(T.IntegerType())
    def place(orders: pa.Array) -> pa.Array:
        return pa.array(np.searchsorted(at, orders.to_numpy(zero_copy_only=False), "right").astype(np.int32))

    return place(F.col("order"))


def _ranges(slim: DataFrame, cuts: list[int], aim: int) -> tuple[DataFrame, list]:
    """slim with the range `part` of each row, and (part, b bytes, c rows) of each range, none overfull if keys differ."""
    for left in range(ROUNDS, -1, -1):
        ranged = materialize(slim.withColumn("part", _placed(cuts)), "shard-ranges")
        sums = sorted(ranged.groupBy("part").agg(F.sum("size").alias("b"), F.count("*").alias("c")).collect(), key=lambda r: r["part"])
        full = {r["part"]: -(-r["c"] // aim) for r in sums if r["c"] > OVERFULL * aim}
        if not full or not left:
            break
        found = set(cuts)
        for n in sorted(set(full.values())):
            own = ranged.filter(F.col("part").isin([p for p, k in full.items() if k == n]))
            for r in own.groupBy("part").agg(F.percentile_approx("order", [i / n for i in range(1, n)], 10 * n + 1_000).alias("q"), F.min("order").alias("lo")).collect():
                found |= {q for q in r["q"] if q > r["lo"]}
        if len(found) == len(cuts):
            break
        cuts = sorted(found)
    return ranged, sums


def shard(docs: DataFrame, shards: int = 24, key: str = "doc_id", text: str = "text", sample_keys: int = SAMPLE_KEYS) -> DataFrame:
    """(key, size, text_crc32, law, shard, slot, grown_shard), one row for each row of docs; law is always `bytes`.

    Null text has size 8. Ties in key order are broken by id, then size; rows equal in all are interchangeable. An
    empty table gives an empty result; shards may be empty if there are fewer records than shards.
    """
    spark = docs.sparkSession
    slim = materialize(_slim(docs, key, text), "shard-keys")
    total, rows = slim.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count("*")).first()
    n = min(MOST_RANGES, max(shards * RANGES_A_SHARD, rows // RANGE_ROWS))
    cuts = splitters(slim, total, n, sample_keys)

    ranged, sums = _ranges(slim.drop("draw"), cuts, max(RANGE_ROWS, rows // MOST_RANGES))
    starts, run = [], 0
    for r in sums:
        starts.append((r["part"], run))
        run += r["b"]
    before = F.broadcast(spark.createDataFrame(starts, "part int, bytes_before bigint"))  # one row a range: MOST_RANGES at most
    w = Window.partitionBy("part").orderBy("order", "k", "size")
    upto = F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, -1))
    position = F.col("bytes_before") + F.coalesce(upto, F.lit(0)) + F.floor(F.col("size") / 2)
    number = F.least(F.lit(shards - 1), F.floor(position.cast("decimal(38,0)") * shards / F.lit(max(total, 1)))).cast("int")
    placed = ranged.join(before, "part").select("k", "size", "text_crc32", "part", number.alias("shard"), F.row_number().over(w).alias("nth"))
    placed = materialize(placed, "shard-places")
    # a range may be cut by a shard's end: rows of each (range, shard), a bounded table
    each = sorted(placed.groupBy("shard", "part").agg(F.count("*").alias("c"), F.min("nth").alias("lo")).collect(), key=lambda r: (r["shard"], r["part"]))
    base, run, last = [], 0, None
    for r in each:
        run = 0 if r["shard"] != last else run
        last = r["shard"]
        base.append((r["shard"], r["part"], run - r["lo"]))
        run += r["c"]
    offset = F.broadcast(spark.createDataFrame(base, "shard int, part int, shift bigint"))
    return placed.join(offset, ["shard", "part"]).select(
        F.col("k").alias(key), "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("nth") + F.col("shift")).cast("bigint").alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
