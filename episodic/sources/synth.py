"""Synthetic spike trains: inhomogeneous Poisson background with planted chains of causes.

Every random draw is a hash of the seed and the row, so the data do not depend on partitions. Each symbol and
millisecond holds an event with a chance that follows a slow modulation above the base rate; an event of a chain's node
triggers the next node with the chain's strength after a delay within its limits. The defaults give about 50,000 events
in 60 s: 46,800 of the background and the rest of one short and one long chain.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from episodic.model import Episode, Interval

MS = 1_000


@dataclass(frozen=True)
class Chain:
    """A planted chain; delays in microseconds, strength the chance that a node triggers the next."""

    nodes: tuple[str, ...]
    low: int = 5 * MS
    high: int = 10 * MS
    strength: float = 0.95
    starts: float = 8.0

    @property
    def episode(self) -> Episode:
        return Episode(self.nodes, tuple(Interval(self.low, self.high) for _ in self.nodes[1:]))


DEFAULT_CHAINS = (Chain(("s0", "s1", "s2")), Chain(("s10", "s11", "s12", "s13", "s14", "s15")))


def _uniform(seed: int, *cols) -> Column:
    return F.pmod(F.xxhash64(F.lit(seed), *[F.lit(c) if isinstance(c, str | int) and not isinstance(c, Column) else c for c in cols]), F.lit(1 << 40)) / F.lit(float(1 << 40))


def synth_spikes(spark: SparkSession, seed: int = 1, n_sym: int = 26, rate_hz: float = 20.0, seconds: int = 60, chains: tuple[Chain, ...] = DEFAULT_CHAINS, modulation: float = 0.5, period_s: float = 5.0) -> DataFrame:
    """(stream_key, sym, t, eid) of a recording; n_sym * rate_hz * seconds * (1 + modulation) background events in expectation, plus chains."""
    cells = spark.range(n_sym * seconds * 1000).select((F.col("id") % n_sym).alias("s"), F.floor(F.col("id") / n_sym).alias("ms"))
    wave = F.lit(1.0) + F.lit(modulation) * (1 + F.sin(F.col("ms") * (2 * 3.141592653589793 / (period_s * 1000)) + F.col("s")))
    fired = cells.filter(_uniform(seed, F.lit("base"), F.col("s"), F.col("ms")) < wave * (rate_hz / 1000))
    spread = F.floor(_uniform(seed, F.lit("at"), F.col("s"), F.col("ms")) * MS)
    out = fired.select(F.concat(F.lit("s"), F.col("s")).alias("sym"), (F.col("ms") * MS + spread).cast("bigint").alias("t"))
    for c, chain in enumerate(chains):
        n = int(chain.starts * seconds)
        live = spark.range(n).select("id", F.floor(_uniform(seed, F.lit(f"start{c}"), F.col("id")) * (seconds * 1_000_000)).cast("bigint").alias("t"))
        for i, node in enumerate(chain.nodes):
            if i:
                delay = chain.low + 1 + F.floor(_uniform(seed, F.lit(f"delay{c}.{i}"), F.col("id")) * (chain.high - chain.low))
                live = live.filter(_uniform(seed, F.lit(f"go{c}.{i}"), F.col("id")) < chain.strength).select("id", (F.col("t") + delay).cast("bigint").alias("t"))
            out = out.unionByName(live.select(F.lit(node).alias("sym"), "t"))
    return out.select(F.lit("all").alias("stream_key"), "sym", "t", F.xxhash64("sym", "t").alias("eid"))
