"""Packing in space-filling-curve order.

A document's token counts, hashed to BUCKETS and divided by their length, project to a point in DIMS dimensions; the
point's place on a Hilbert curve is its key. Documents are range-sorted by key, so that neighbours on the curve, which use like words, follow one
another, and the sorted stream of ids is cut into sequences. Documents may be cut, so only the end of the whole corpus
leaves a rest, which is cut into powers of two: nothing is padded.

Texts are encoded once. The encoded rows are written to the shared folder; quantiles of the keys give the ranges, whose
token sums (one number a range) give each range the place where it starts. A range then streams: no group is held.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .runtime import materialize

DIMS, BITS, BUCKETS = 4, 8, 1024
#: Documents and tokens of a range aimed at, and ranges at most: bounds of what the driver holds.
RANGE_TOKENS, MOST_RANGES = 8_000_000, 16_384
#: Texts longer than this are encoded by the library that reads the .json itself.
LONG_TEXT = 1_000_000


def hilbert_keys(points: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Places on the Hilbert curve of integer points (rows) with coordinates below 2 ** bits."""
    x = points.astype(np.uint64).T.copy()
    dims = len(x)
    one = np.uint64(1)
    for level in range(bits - 1, 0, -1):  # from corner codes to turned axes, most significant level first
        bit = one << np.uint64(level)
        below = bit - one
        for d in range(dims):
            high = (x[d] & bit) != 0
            swap = np.where(high, np.uint64(0), (x[0] ^ x[d]) & below)
            x[0] = np.where(high, x[0] ^ below, x[0] ^ swap)
            x[d] ^= swap
    for d in range(1, dims):  # Gray code across the axes
        x[d] ^= x[d - 1]
    turn = np.zeros_like(x[0])
    for level in range(bits - 1, 0, -1):
        bit = one << np.uint64(level)
        turn = np.where((x[-1] & bit) != 0, turn ^ (bit - one), turn)
    x ^= turn
    key = np.zeros_like(x[0])
    for level in range(bits - 1, -1, -1):
        for d in range(dims):
            key = (key << one) | ((x[d] >> np.uint64(level)) & one)
    return key


class Encoder:
    """Ids of a byte-level BPE vocabulary; the same ids as the library of the .json gives, by a faster one if there."""

    def __init__(self, vocabulary: str, ranks: str | None, pattern: str | None, special: dict[str, int]):
        from tokenizers import Tokenizer

        self.plain = Tokenizer.from_file(vocabulary)
        self.fast = None
        if ranks:
            import tiktoken

            table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(ranks, "rb"))}
            self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=table, special_tokens=special)
            self.special = set(special)
        self.axes = np.random.default_rng(71).standard_normal((BUCKETS, DIMS))

    def encode(self, text: str) -> np.ndarray:
        if self.fast is not None and len(text) <= LONG_TEXT:
            return np.array(self.fast.encode(text, allowed_special=self.special, disallowed_special=()), np.uint32)
        return np.array(self.plain.encode(text, add_special_tokens=False).ids, np.uint32)

    def point(self, ids: np.ndarray) -> np.ndarray:
        """Coordinates of the document's unit vector of hashed token counts, squeezed to 2 ** BITS steps each."""
        if not len(ids):
            return np.zeros(DIMS, np.int64)
        bucket = (ids * np.uint32(2654435761)) >> np.uint32(32 - BUCKETS.bit_length() + 1)
        counts = np.bincount(bucket, minlength=BUCKETS).astype(np.float64)
        spread = np.tanh(counts @ self.axes / np.sqrt(counts @ counts))
        return np.minimum(((spread + 1) * (1 << (BITS - 1))).astype(np.int64), (1 << BITS) - 1)


@lru_cache(1)
def _encoder(vocabulary: str, ranks: str | None, pattern: str | None, special: tuple[tuple[str, int], ...]) -> Encoder:
    return Encoder(vocabulary, ranks, pattern, dict(special))


def _encoded(setup: tuple, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = _encoder(*setup)
        for b in batches:
            for s in range(0, b.num_rows, 512):
                part = b.slice(s, 512)
                points, ids, n = [], [], []
                for text in part.column(1):
                    own = enc.encode(text.as_py() or "")
                    points.append(enc.point(own))
                    own = np.r_[own, np.uint32(end_id)].astype("<u4")
                    n.append(len(own))
                    ids.append((own.astype("<u2") if own.max() < 1 << 16 else own).tobytes())
                keys = hilbert_keys(np.array(points)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(keys), pa.array(n, pa.int64()), pa.array(ids, pa.binary())], ["k", "curve", "n", "ids"])

    return run


def cuts_of(start: int, end: int, full: int, length: int, rest: list[tuple[int, int]]) -> Iterator[tuple[int, int, int, int]]:
    """(start, end, sequence, offset) of the pieces of stream places [start, end).

    The first `full` sequences have `length` places; `rest` lists start and length of those after them.
    """
    at = start
    while at < end:
        if at < full * length:
            seq = at // length
            low, size = seq * length, length
        else:
            i = next(i for i, (lo, n) in enumerate(rest) if lo <= at < lo + n)
            seq, (low, size) = full + i, rest[i]
        stop = min(end, low + size)
        yield at, stop, seq, at - low
        at = stop


def tail_sequences(total: int, length: int) -> list[tuple[int, int]]:
    """(start, length) of the sequences after the last full one: the powers of two of the rest, largest first."""
    at, out = total - total % length, []
    for b in range((total % length).bit_length() - 1, -1, -1):
        if (total % length) >> b & 1:
            out.append((at, 1 << b))
            at += 1 << b
    return out


def _pieces(starts: dict[int, int], total: int, length: int):
    full, rest = total // length, tail_sequences(total, length)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, at = None, 0
        for b in batches:
            out = []
            for key, own, n, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
                if own != part:
                    part, at = own, starts[own]
                raw = raw.as_buffer()
                ids = np.frombuffer(raw, "<u4" if raw.size == 4 * n else "<u2").astype("<u4")
                for a, z, seq, offset in cuts_of(at, at + n, full, length, rest):
                    out.append((key, a - at, z - a, zlib.crc32(ids[a - at : z - at].tobytes()), n, seq, offset))
                at += n
            cols = list(zip(*out, strict=True)) or [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], b.schema.field(0).type), *(pa.array(c, pa.int64()) for c in cols[1:])], ["k", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, vocabulary: str, ranks: str | None = None, pattern: str | None = None, special: dict[str, int] | None = None, length: int = 2048, end_id: int = 1, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, start, length, ids_crc32, doc_tokens, sequence_id, offset) of each piece of each row of docs.

    vocabulary: path of the byte-level BPE .json; ranks, pattern and special: the same vocabulary for the faster
    library, optional. Each row's ids, then end_id, lie in consecutive pieces; null text is empty, so one piece of
    end_id. Rows equal in key and text are packed twice. An empty table gives an empty result.
    """
    kind = docs.schema[key].dataType.simpleString()
    setup = (vocabulary, ranks, pattern, tuple(sorted((special or {}).items())))
    plan = docs.select(F.col(key).alias("k"), F.col(text).alias("t"))
    encoded = plan.mapInArrow(_encoded(setup, end_id), f"k {kind}, curve bigint, n bigint, ids binary")
    # ties on the curve are ordered by a hash of the id, so that a group of copies can be cut by ranges
    place = F.shiftleft("curve", 31).bitwiseOR(F.pmod(F.xxhash64("k"), F.lit(1 << 31)))
    stored = materialize(encoded.withColumn("place", place).drop("curve"), "encoded")
    total, rows = stored.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    ranges = int(min(MOST_RANGES, max(1, total // RANGE_TOKENS, min(rows // 500, 32))))
    quantiles = [i / ranges for i in range(1, ranges)]
    cuts = np.unique(np.array(stored.agg(F.percentile_approx("place", quantiles, max(20_000, 10 * ranges))).first()[0] or [], np.int64)) if quantiles and rows else np.zeros(0, np.int64)

    @F.pandas_udf(T.LongType())
    def part_of(places):
        import pandas as pd

        return pd.Series(np.searchsorted(cuts, places.to_numpy(np.int64), "right"))

    ranged = stored.withColumn("part", part_of("place"))
    sums = {r["part"]: r["n"] for r in ranged.select("part", "n").groupBy("part").agg(F.sum("n").alias("n")).collect()}
    starts, at = {}, 0
    for p in sorted(sums):
        starts[p] = at
        at += sums[p]
    order = ranged.repartition(ranges, "part").sortWithinPartitions("part", "place", "k", "n")
    schema = f"k {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"
    return order.select("k", "part", "n", "ids").mapInArrow(_pieces(starts, total, length), schema).withColumnRenamed("k", key)
