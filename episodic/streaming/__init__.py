"""Continuous counting over Structured Streaming.

Events of a stream key wait in state until the watermark has passed them, so that they are counted in order whatever
order they came in; then each episode's machine advances. State holds the waiting events, for every episode the times
that can still be extended (all within its reach) and the count. Events later than the watermark are dropped by Spark.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from episodic.functions.automata import ListAutomaton
from episodic.model import Episode

OUT = "stream_key string, episode_id bigint, support bigint, upto bigint"
STATE = "waiting string, held string, counts string"


def _advance(episodes: dict[int, Episode]):
    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        waiting, held, counts = (json.loads(x) for x in state.get) if state.exists else ([], {}, {})
        for f in frames:
            waiting += f[["t", "eid", "sym"]].values.tolist()
        mark = state.getCurrentWatermarkMs() * 1000
        ready = sorted((int(t), int(e), s) for t, e, s in waiting if t < mark)
        waiting = [(int(t), int(e), s) for t, e, s in waiting if t >= mark]
        rows = []
        for i, e in episodes.items():
            m = ListAutomaton(e)
            m.take(held.get(str(i), []))
            n = counts.get(str(i), 0)
            before = n
            for t, _, s in ready:
                n += m.step(s, t)
            held[str(i)], counts[str(i)] = m.lists(), n
            if n != before:
                rows.append((key[0], i, n, ready[-1][0]))
        state.update((json.dumps(waiting), json.dumps(held), json.dumps(counts)))
        if waiting:
            first = min(t for t, _, _ in waiting)  # woken as soon as the watermark passes it, even without new events
            state.setTimeoutTimestamp(max(first // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(rows, columns=["stream_key", "episode_id", "support", "upto"])

    return run


def stream_count(events: DataFrame, episodes: dict[int, Episode], watermark: str = "10 minutes") -> DataFrame:
    """A streaming DataFrame of (stream_key, episode_id, support, upto): a row whenever a support has grown."""
    timed = events.withColumn("at", F.timestamp_micros("t")).withWatermark("at", watermark)
    return timed.groupBy("stream_key").applyInPandasWithState(_advance(episodes), OUT, STATE, "update", GroupStateTimeout.EventTimeTimeout)


def latest_supports(spark: SparkSession, path: str) -> DataFrame:
    """(stream_key, episode_id, support) from what upsert_sink wrote: the newest row of each."""
    held = spark.read.schema("stream_key string, episode_id bigint, support bigint, upto bigint, batch bigint").parquet(path)
    newest = F.max(F.struct("batch", "support")).alias("n")
    return held.groupBy("stream_key", "episode_id").agg(newest).select("stream_key", "episode_id", F.col("n.support").alias("support"))


def upsert_sink(path: str):
    """A foreachBatch function that keeps a micro-batch's rows in its own folder; a batch that runs again replaces it."""

    def write(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={batch}")

    return write


def write_days(ev: DataFrame, path: str, width: int) -> int:
    """ev as one folder entry for each slice of `width`, written in order of time; returns the number of slices."""
    sliced = ev.withColumn("slice", F.floor(F.col("t") / width))
    days = [r["slice"] for r in sliced.select("slice").distinct().orderBy("slice").collect()]
    for d in days:
        sliced.filter(F.col("slice") == d).drop("slice").coalesce(1).write.mode("append").parquet(path)
    return len(days)


def replay(spark: SparkSession, path: str, episodes: dict[int, Episode], out: str, checkpoint: str, watermark: str = "0 seconds", files_a_batch: int = 1) -> DataFrame:
    """Feeds stored event files through stream_count, in order of file, and returns the last supports.

    Each micro-batch takes files_a_batch files, continues the machines from stored state, and writes what grew to the
    folder `out`. The last events still wait for the watermark when files end: add a closing event far enough ahead to
    count them.
    """
    from episodic.sources import read_event_stream

    counted = stream_count(read_event_stream(spark, path, files_a_batch=files_a_batch), episodes, watermark)
    q = counted.writeStream.foreachBatch(upsert_sink(out)).outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return latest_supports(spark, out)


def interval_pairs(views: DataFrame, clicks: DataFrame, high: int, watermark: str = "0 seconds") -> DataFrame:
    """(stream_key, view, click): a streaming join of two event streams on key and 0 < delay <= high microseconds.

    Both sides carry a watermark, so that rows which can't match any more leave the state.
    """
    a = views.select("stream_key", F.col("eid").alias("view"), F.timestamp_micros("t").alias("ta")).withWatermark("ta", watermark)
    b = clicks.select(F.col("stream_key").alias("other"), F.col("eid").alias("click"), F.timestamp_micros("t").alias("tb")).withWatermark("tb", watermark)
    within = F.expr(f"stream_key = other AND tb > ta AND tb <= ta + INTERVAL {high} MICROSECONDS")
    return a.join(b, within).select("stream_key", "view", "click")


def split_late(spark: SparkSession, path: str, delay: int, out: str, checkpoint: str, files_a_batch: int = 1) -> DataFrame:
    """(batch, on_time, late): how many events of each micro-batch come later than `delay` microseconds behind the newest
    event of the batches before. Spark drops such events in stateful queries; this counts them on the side."""
    from episodic.sources import read_event_stream

    newest = [None]

    def write(rows: DataFrame, batch: int) -> None:
        late = F.lit(False) if newest[0] is None else F.col("t") < newest[0] - delay
        n, late_n, hi = rows.agg(F.count("*"), F.coalesce(F.sum(late.cast("bigint")), F.lit(0)), F.max("t")).first()
        if n:
            spark.createDataFrame([(n - late_n, late_n)], "on_time bigint, late bigint").write.mode("overwrite").parquet(f"{out}/batch={batch}")
            newest[0] = hi if newest[0] is None else max(newest[0], hi)

    q = read_event_stream(spark, path, files_a_batch=files_a_batch).writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema("on_time bigint, late bigint, batch bigint").parquet(out)


def windowed_counts(events: DataFrame, width: str, slide: str | None = None, watermark: str = "0 seconds") -> DataFrame:
    """(start, sym, n) of tumbling or sliding windows, streaming or batch."""
    timed = events.withColumn("at", F.timestamp_micros("t"))
    if events.isStreaming:
        timed = timed.withWatermark("at", watermark)
    w = F.window("at", width, slide) if slide else F.window("at", width)
    return timed.groupBy(w, "sym").agg(F.count("*").alias("n")).select(F.unix_micros(F.col("window.start")).alias("start"), "sym", "n")


def once(events: DataFrame, watermark: str) -> DataFrame:
    """Replayed events without repeats of (stream_key, eid) inside the watermark."""
    return events.withColumn("at", F.timestamp_micros("t")).withWatermark("at", watermark).dropDuplicatesWithinWatermark(["stream_key", "eid"]).drop("at")
