"""Exact dedup by deterministic block naming.

The normalised text is cut into fixed-size blocks. The distinct blocks of the corpus, sorted, get integer names; then
adjacent pairs of names are named in the same way, level by level, until each document is one name. Equal documents
have equal names and different documents different ones, with no chance of a collision: blocks are compared byte by
byte, pairs as pairs of integers.

Names come from distinct values only (hash aggregates that combine before the shuffle), and join back to occurrences
by a fixed-size key, so a block that a third of all rows hold is one row a task on its way to a name, and the join is
one that adaptive execution can split. Each level halves the rows; documents of one block leave at the first level.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .runtime import materialize, passing

#: Bytes of a block. Most documents are one block; a row never holds more than this of a text.
BLOCK_BYTES = 8192
_AS_SPACE = bytes.maketrans(b"\t\n\v\f\r", b"     ")
_RUN = re.compile(b" {2,}")


def normalised(text: bytes) -> bytes:
    """The UTF-8 text with each run of ASCII white space as one space."""
    text = text.translate(_AS_SPACE)
    return _RUN.sub(b" ", text) if b"  " in text else text


def _bytes_of(texts: pa.Array) -> Iterator[bytes]:
    """UTF-8 of each text, straight from the Arrow buffer; null is empty."""
    texts = texts.cast(pa.large_string()).fill_null("")
    _, off, data = texts.buffers()
    at = np.frombuffer(off, np.int64)[texts.offset : texts.offset + len(texts) + 1].tolist() if len(texts) else [0]
    view = memoryview(data) if data is not None else memoryview(b"")
    for a, z in zip(at[:-1], at[1:], strict=True):
        yield bytes(view[a:z])


def _blocks(docs: DataFrame, key: str, text: str, size: int, whole: bool) -> DataFrame:
    """(row, k, sha, n, pos, digest) of each block of each row of docs, and with `whole` its bytes as `block`."""
    kind = docs.schema[key].dataType.simpleString()
    names = ["row", "k", "sha", "n", "pos", "digest", *(["block"] if whole else [])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for s in range(0, b.num_rows, 1024):
                part = b.slice(s, 1024)
                row, shas, ns, places, digests, blocks = [], [], [], [], [], []
                for r, raw in enumerate(_bytes_of(part.column(2))):
                    norm = normalised(raw)
                    sha = hashlib.sha256(norm).digest()
                    cut = [norm] if len(norm) <= size else [norm[i : i + size] for i in range(0, len(norm), size)]
                    for i, x in enumerate(cut):
                        row.append(r)
                        shas.append(sha)
                        ns.append(len(cut))
                        places.append(i)
                        digests.append(sha if len(cut) == 1 else hashlib.sha256(x).digest())
                    if whole:
                        blocks += cut
                own = pa.array(row, pa.int64())
                cols = [part.column(0).take(own), part.column(1).take(own), pa.array(shas, pa.binary()), pa.array(ns, pa.int32()), pa.array(places, pa.int32()), pa.array(digests, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols + ([pa.array(blocks, pa.binary())] if whole else []), names)

    schema = f"row bigint, k {kind}, sha binary, n int, pos int, digest binary" + (", block binary" if whole else "")
    return docs.select(F.monotonically_increasing_id().alias("row"), F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(run, schema)


def _named(distinct: DataFrame, *by: str) -> DataFrame:
    """distinct rows with the integer name that their sorted place gives them; 0 is left for 'no neighbour'."""
    return distinct.orderBy(*by).withColumn("name", F.monotonically_increasing_id() + 1)


def _name_blocks(docs: DataFrame, key: str, text: str, size: int) -> DataFrame:
    """(k, sha, n, pos, name). Blocks are told apart byte by byte: the digest only carries the join, and is checked."""
    strings = _blocks(docs, key, text, size, True).groupBy("digest", "block").agg(F.lit(1).alias("one"))
    names = materialize(_named(strings.groupBy("digest").agg(F.count("*").alias("variants")), "digest"), "block-names")
    if names.filter("variants > 1").isEmpty():
        return _blocks(docs, key, text, size, False).join(names.select("digest", "name"), "digest").drop("digest")
    full = materialize(_named(strings.drop("one"), "digest", "block"), "block-names")  # one digest for two blocks: compare the bytes
    return _blocks(docs, key, text, size, True).join(full, ["digest", "block"]).drop("digest", "block")


def identities(docs: DataFrame, key: str = "doc_id", text: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(row, k, sha, level, name) of each row of docs: equal normalised texts have equal (level, name), others not."""
    level, done = 0, []
    current = materialize(_name_blocks(docs, key, text, block_bytes), "names")
    while True:
        done.append(current.filter("n = 1").select("row", "k", "sha", F.lit(level).alias("level"), "name"))
        rest = current.filter("n > 1")
        if rest.isEmpty():
            break
        level += 1
        half = F.shiftright("pos", 1)
        left, right = (F.max(F.when(F.col("pos") % 2 == i, F.col("name"))) for i in (0, 1))
        pairs = rest.groupBy("row", "k", "sha", "n", half.alias("pos")).agg(left.alias("l"), F.coalesce(right, F.lit(0)).alias("r"))
        pairs = materialize(pairs.withColumn("n", F.shiftright(F.col("n") + 1, 1)), "pairs")
        names = materialize(_named(pairs.groupBy("l", "r").agg(F.lit(1).alias("one")), "l", "r").drop("one"), "pair-names")
        current = materialize(pairs.join(names, ["l", "r"]).drop("l", "r"), "names")
    return reduce(DataFrame.unionByName, done)


def exact_groups(docs: DataFrame, key: str = "doc_id", text: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(key, keep_id, group_size, kept, text_sha256), one row for each row of docs, dropped ones too.

    Null text is empty. Of equal texts the smallest key stays; null keys come after all others and stay only among
    themselves. Rows that repeat a key are documents of their own, and group_size counts them all; where several rows
    of a group have its smallest key, kept is true for each (drop_exact_copies leaves one). An empty table gives an
    empty result.
    """
    names = identities(docs, key, text, block_bytes)
    # written before the join, whose sides are then both plain shuffles that adaptive execution can split where a group is hot
    groups = materialize(names.groupBy("level", "name").agg(F.min("k").alias("keep_id"), F.count("*").alias("group_size")), "groups")
    return names.join(groups, ["level", "name"]).select(
        F.col("k").alias(key), "keep_id", "group_size", F.col("k").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256")
    )


def drop_exact_copies(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of docs that stay, with their own columns: one of each group of equal texts.

    The copies are joined away by key and the text's digest, in a sort-merge join at every size: their list grows with
    the corpus. Of rows that repeat key and text one stays.
    """
    with passing("exact-copies", "repeated-rows"):
        groups = materialize(exact_groups(docs, key, text).select(F.col(key).alias("__k"), F.unhex("text_sha256").alias("__s"), "kept"), "exact-groups")
        gone = materialize(groups.filter("NOT kept").select("__k", "__s").distinct(), "exact-copies")
        same = materialize(groups.filter("kept").groupBy("__k", "__s").agg(F.count("*").alias("times")).filter("times > 1").select("__k", "__s"), "repeated-rows")

    @F.arrow_udf(T.BinaryType())
    def sha_of(texts: pa.Array) -> pa.Array:
        return pa.array([hashlib.sha256(normalised(t)).digest() for t in _bytes_of(texts)], pa.binary())

    marked = docs.withColumn("__sha", sha_of(F.col(text)))
    on = lambda t: marked[key].eqNullSafe(t["__k"]) & (marked["__sha"] == t["__s"])
    stay = marked.join(gone.hint("merge"), on(gone), "left_anti")  # one plan at every size
    if same.isEmpty():
        return stay.drop("__sha")
    once = stay.join(same, on(same), "left_semi").dropDuplicates([key, "__sha"])
    return stay.join(same, on(same), "left_anti").unionByName(once).drop("__sha")
