"""Comparing the members of groups in bounded tiles: no task ever holds more than two tiles of a group."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def in_tiles(members: DataFrame, group: str, size: str, member: str, tile: int, parts: int | None = None) -> DataFrame:
    """members, each copied to the tile pairs of its group that need it, sorted in runs of (group, i, j).

    A group of `size` members has ceil(size / tile) tiles, dealt by hash, and a run for each pair of tiles. `own` is the
    member's tile. Groups of one tile are one run; no pair of members is made here. `parts` partitions, or Spark's number.
    """
    tiles = F.ceil(F.col(size) / tile).cast("int")
    dealt = members.withColumn("tiles", tiles).withColumn("own", F.pmod(F.xxhash64(member, F.lit(7)), F.col("tiles")).cast("int"))
    other = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    runs = other.withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other")).drop("other", "tiles")
    dealt = runs.repartition(parts, group, "i", "j") if parts else runs.repartition(group, "i", "j")
    return dealt.sortWithinPartitions(group, "i", "j", "own")


def runs_of(batches: Iterator[pa.RecordBatch], key: list[str]) -> Iterator[pa.Table]:
    """The runs of rows with equal key, whole, from sorted batches."""
    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        if not b.num_rows:
            continue
        keys = list(zip(*(b.column(b.schema.get_field_index(k)).to_pylist() for k in key), strict=True))
        at = 0
        for r, k in enumerate(keys):
            if k != last:
                if r > at:
                    held.append(b.slice(at, r - at))
                if held:
                    yield pa.Table.from_batches(held)
                held, at, last = [], r, k
        held.append(b.slice(at))
    if held:
        yield pa.Table.from_batches(held)


def over_runs(tiled: DataFrame, key: list[str], kernel: Callable[[pa.Table], pa.Table | None], schema: str, rows: int = 20_000) -> DataFrame:
    """kernel over each run; its tables are joined into batches of about `rows`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for table in runs_of(batches, key):
            out = kernel(table)
            if out is not None and out.num_rows:
                held.append(out)
                n += out.num_rows
            if n >= rows:
                yield from pa.concat_tables(held).combine_chunks().to_batches()
                held, n = [], 0
        if held:
            yield from pa.concat_tables(held).combine_chunks().to_batches()

    return tiled.mapInArrow(run, schema)


def star_edges(ids: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For linked places (i, j): an edge from each place to the smallest id reachable through them."""
    nodes, inv = np.unique(np.r_[i, j], return_inverse=True)
    x, y = inv[: len(i)], inv[len(i) :]
    root = ids[nodes]
    while True:
        low = np.minimum(root[x], root[y])
        new = root.copy()
        np.minimum.at(new, x, low)
        np.minimum.at(new, y, low)
        if (new == root).all():
            break
        root = new
    far = root != ids[nodes]
    return ids[nodes][far], root[far]
