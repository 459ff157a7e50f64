"""Streaming kernels over runs of equal keys in sorted partitions: no group is a task of its own."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

#: Numbers in the lists of a batch of rows that leaves a task, beyond which the batch is sent.
MOST_NUMBERS = 1_000_000


def _starts(b: pa.RecordBatch, places: list[int]) -> list[int]:
    """The rows of a batch at which another key begins; the first is one."""
    cut = np.zeros(b.num_rows - 1, bool)
    for c in (b.column(i) for i in places):
        if c.null_count:
            v = c.to_pylist()
            cut |= np.array([x != y for x, y in zip(v[1:], v, strict=False)], bool)
        else:
            cut |= pc.not_equal(c.slice(1), c.slice(0, len(c) - 1)).to_numpy(zero_copy_only=False)
    return [0, *(np.flatnonzero(cut) + 1).tolist()]


def _pieces(batches: Iterator[pa.RecordBatch], key: list[str], most: int | None = None) -> Iterator[tuple[tuple, pa.Table]]:
    """(key, rows) of each run of equal keys, in pieces of about `most` rows if that is given."""
    held: list[pa.RecordBatch] = []
    last, n = None, 0
    for b in batches:
        if not b.num_rows:
            continue
        places = [b.schema.get_field_index(k) for k in key]
        starts = _starts(b, places)
        for at, end in zip(starts, [*starts[1:], b.num_rows], strict=True):
            k = tuple(b.column(i)[at].as_py() for i in places)
            if k != last:
                if held:
                    yield last, pa.Table.from_batches(held)
                held, last, n = [], k, 0
            held.append(b.slice(at, end - at))
            n += end - at
            if most and n >= most:
                yield last, pa.Table.from_batches(held)
                held, n = [], 0
    if held:
        yield last, pa.Table.from_batches(held)


def scan_runs(df: DataFrame, key: list[str], order: list[str], begin: Callable[[tuple], object], schema: str, target: pa.Schema, most: int = 200_000) -> DataFrame:
    """For each run of rows with equal key, in the given order: begin(key) gives a scanner, whose feed(table) gets the run
    in pieces and whose rows() is the result. A task holds a piece and the scanner, however long the run."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, scanner = None, None
        for k, table in _pieces(batches, key, most):
            if scanner is None or k != last:
                if scanner is not None and (rows := scanner.rows()):
                    yield as_batch(rows, target)
                last, scanner = k, begin(k)
            scanner.feed(table)
        if scanner is not None and (rows := scanner.rows()):
            yield as_batch(rows, target)

    return df.repartition(*key).sortWithinPartitions(*key, *order).mapInArrow(run, schema)


def over_runs(df: DataFrame, key: list[str], order: list[str], kernel: Callable[[pa.Table], Iterable[tuple]], schema: str, target: pa.Schema, rows: int = 20_000) -> DataFrame:
    """kernel(run) -> rows, for each run of rows with equal key in the given order; rows leave in batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from in_batches((row for _, table in _pieces(batches, key) for row in kernel(table)), target, rows)

    return df.repartition(*key).sortWithinPartitions(*key, *order).mapInArrow(run, schema)


def in_batches(rows: Iterable[tuple], target: pa.Schema, most: int) -> Iterator[pa.RecordBatch]:
    """The rows in batches of `most`, or fewer where their lists have MOST_NUMBERS numbers before that."""
    lists = [i for i, x in enumerate(target.types) if pa.types.is_list(x)]
    out, numbers = [], 0
    for row in rows:
        out.append(row)
        numbers += sum(len(row[i]) for i in lists if row[i] is not None)
        if len(out) >= most or numbers >= MOST_NUMBERS:
            yield as_batch(out, target)
            out, numbers = [], 0
    if out:
        yield as_batch(out, target)


def as_batch(rows: list[tuple], target: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), target, strict=True)], schema=target)


def fold_rows(df: DataFrame, key: list[str], order: list[str], kernel: Callable[[tuple, list[tuple]], tuple], schema: str, target: pa.Schema) -> DataFrame:
    """kernel(key, rows) -> one row, for each run of small rows with equal key; rows are the other columns as tuples.

    Cheaper than over_runs where runs are many and short: columns become Python values once a batch.
    """
    rest = [c for c in df.columns if c not in key]
    n = len(key)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, held = None, []
        for b in batches:
            out = []
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                k = row[:n]
                if k != current:
                    if held:
                        out.append(kernel(current, held))
                    current, held = k, []
                held.append(row[n:])
            if out:
                yield as_batch(out, target)
        if held:
            yield as_batch([kernel(current, held)], target)

    return df.select(*key, *rest).repartition(*key).sortWithinPartitions(*key, *order).mapInArrow(run, schema)


def fold_lists(df: DataFrame, key: list[str], order: list[str], lists: str, begin: Callable[[], object], feed: Callable[[object, np.ndarray], object], result: Callable[[tuple, object], tuple], schema: str, target: pa.Schema) -> DataFrame:
    """result(key, state) -> one row, for each run of rows with equal key; state is begin() and then feed(state, numbers)
    for the list of each row in the given order.

    A list is a slice of its batch, never Python numbers: a task holds one batch and the state, however long the lists.
    """
    n = len(key)

    def folded(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        current, state = None, None
        for b in batches:
            column = b.column(n)
            numbers, at = column.values.to_numpy(), column.offsets.to_numpy()
            for i, k in enumerate(zip(*(b.column(c).to_pylist() for c in range(n)), strict=True)):
                if k != current:
                    if current is not None:
                        yield result(current, state)
                    current, state = k, begin()
                state = feed(state, numbers[at[i] : at[i + 1]])
        if current is not None:
            yield result(current, state)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from in_batches(folded(batches), target, 20_000)

    return df.select(*key, lists, *order).repartition(*key).sortWithinPartitions(*key, *order).mapInArrow(run, schema)
