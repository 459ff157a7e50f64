"""MinHash near-dedup: one-permutation hashing, optimal densification, banded buckets, star-shaped candidate edges.

A document is the set of its distinct k-word shingles. One hash of each shingle falls into one of SLOTS bins and each
bin keeps its least hash; an empty bin borrows from the bin that its own probe sequence reaches first. Bands of slots
are bucket keys. Documents with one and the same set are first one class, represented by the smallest id.

A bucket of m classes gives at most 2(m-1) candidate edges: a star to its smallest id and one to a member drawn by
hash. Every candidate is confirmed on the full sets. Stars can miss a link between two members that neither centre is
linked with, so buckets whose members are still in different components are compared in bounded tiles: first by slot
values, which leave the members that may have a link, then those by their full sets. Tiles give stars, never all pairs. Bands are chosen so that a pair right at the
threshold shares no bucket with a chance under 1e-8.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .runtime import materialize, passing
from .tiles import in_tiles, over_runs, star_edges
from .wordhash import NOT_WHITE, mix, spans, text_chunks, word_hashes

SLOTS = 160
#: Standard deviations that the share of equal slots of a pair at the threshold may fall short of it (one in 10 ** 9).
SHORT = 6.0
TILE = 512
#: Ids of candidates that may be broadcast (8 bytes each).
BROADCAST_IDS = 2_000_000
_PROBES = 2048
_SALTS = mix(np.arange(1, 65, dtype=np.uint64))


def band_rows(percent: int) -> int:
    """Slots of a band: with SLOTS // rows bands the chance to miss a pair at the threshold stays under 1e-8."""
    for rows in (8, 5, 4, 2, 1):
        if (1 - (percent / 100) ** rows) ** (SLOTS // rows) < 1e-8:
            return rows
    raise ValueError(f"a similarity of {percent} % is too low for {SLOTS} slots")


def least_agreement(percent: int) -> int:
    """Equal slots below which two documents are taken as not similar without a look at their full sets."""
    p = percent / 100
    return math.floor(SLOTS * p - SHORT * math.sqrt(SLOTS * p * (1 - p)))


def _probe_table() -> np.ndarray:
    draws = mix(np.arange(SLOTS * _PROBES, dtype=np.uint64) + np.uint64(0xA5A5))
    return ((draws >> np.uint64(32)) * np.uint64(SLOTS) >> np.uint64(32)).astype(np.int64).reshape(_PROBES, SLOTS)


def shingle_sets(texts: pa.Array, k: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text; one for the whole sequence if it has under k words."""
    for first, last, data, off in text_chunks(texts):
        starts, ends, at = spans(data, off, NOT_WHITE)
        words, _ = word_hashes(data, starts, ends)
        joined = np.zeros(max(0, len(words) - k + 1), np.uint64)
        for i in range(k if len(joined) else 0):
            joined += words[i : i + len(joined)] * _SALTS[i] ^ _SALTS[i]
        joined = mix(joined + np.uint64(k))
        for r in range(last - first):
            a, b = at[r], at[r + 1]
            if b - a >= k:
                yield np.unique(joined[a : b - k + 1])
            elif b > a:
                yield mix(np.array([(words[a:b] * _SALTS[: b - a] ^ _SALTS[: b - a]).sum() + np.uint64(b - a)], np.uint64))
            else:
                yield np.zeros(0, np.uint64)


def slot_values(shingles: np.ndarray, probes: np.ndarray) -> np.ndarray:
    """The least shingle of each bin; the sorted order of shingles is also that of bins, so the first of each is least."""
    bins = ((shingles >> np.uint64(32)) * np.uint64(SLOTS) >> np.uint64(32)).astype(np.int64)
    first = np.flatnonzero(np.r_[True, bins[1:] != bins[:-1]])
    out, full = np.zeros(SLOTS, np.uint64), np.zeros(SLOTS, bool)
    out[bins[first]], full[bins[first]] = shingles[first], True
    need = np.flatnonzero(~full)
    for p in probes:
        if not len(need):
            break
        donor = p[need]
        ok = full[donor]
        out[need[ok]] = out[donor[ok]]
        need = need[~ok]
    out[need] = shingles[0]
    return mix(out)


def _print(shingles: np.ndarray) -> bytes:
    """What a set of shingles is known by."""
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest()


def _sketches(k: int, rows: int):
    """(id, h, g, n, print, bands, slots) of batches of (id, h, g, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        probes = _probe_table()
        bands = SLOTS // rows
        number = np.arange(bands, dtype=np.uint64)
        fold = _SALTS[:rows]
        for b in batches:
            n, prints, keys, slots = [], [], [], []
            for s in shingle_sets(b.column(3), k):
                n.append(len(s))
                if len(s):
                    v = slot_values(s, probes)
                    prints.append(_print(s))
                    keys.append(mix((v[: bands * rows].reshape(bands, rows) * fold).sum(1) + number * np.uint64(0x9E3779B97F4A7C15)).view(np.int64))
                    slots.append(v.astype(np.uint32).tobytes())
                else:
                    prints.append(None)
                    keys.append(np.zeros(0, np.int64))
                    slots.append(None)
            cols = [*b.columns[:3], pa.array(n, pa.int64()), pa.array(prints, pa.binary()), _lists(keys), pa.array(slots, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, ["id", "h", "g", "n", "print", "bands", "slots"])

    return run


def _lists(xs: list[np.ndarray]) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum([len(x) for x in xs])].astype(np.int32)), pa.array(np.concatenate([*xs, np.zeros(0, np.int64)])))


def _sets(k: int):
    """(node, shingles) of batches of (node, print, text); a text that its node's print is not of is left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = list(shingle_sets(b.column(2), k))
            own = [i for i, (s, p) in enumerate(zip(sets, b.column(1).to_pylist(), strict=True)) if _print(s) == p]
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(own, pa.int64())), _lists([sets[i].view(np.int64) for i in own])], ["id", "shingles"])

    return run


def _full_sets(nodes: DataFrame, classes: DataFrame, texts: DataFrame, words: int) -> DataFrame:
    """(id, shingles) of the nodes in column c: full sets are several times as large as the texts, so they are made for
    candidates only. A node's text is found by the key and hash of its first row, and told from others by the print of
    its set. The list of nodes is broadcast while it has BROADCAST_IDS entries at most, else joined by shuffle."""
    own = classes.select(F.col("node").alias("c"), F.col("id").alias("k0"), F.col("h").alias("h0"), "print")
    wanted = materialize(nodes.distinct().join(own, "c"), "candidates")
    n = wanted.count()
    met = texts.join(F.broadcast(wanted) if n <= BROADCAST_IDS else wanted, (texts["id"] == wanted["k0"]) & (texts["h"] == wanted["h0"]))
    sets = materialize(met.select("c", "print", "t").mapInArrow(_sets(words), "id bigint, shingles array<bigint>"), "shingle-sets")
    # rows that repeat key and text give a node's set more than once
    return sets if sets.count() == n else materialize(sets.dropDuplicates(["id"]), "shingle-sets")


def _confirmed(pairs: DataFrame, classes: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough, in exact integer arithmetic."""
    sets = _full_sets(pairs.select(F.explode(F.array("a", "b")).alias("c")), classes, texts, words)
    left = sets.select(F.col("id").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("id").alias("b"), F.col("shingles").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    met = pairs.join(left, "a").join(right, "b").withColumn("both", both)
    return met.filter(F.col("both") * 100 >= (F.size("sa") + F.size("sb") - F.col("both")) * percent).select("a", "b")


def _plausible(rows: int, percent: int):
    """The members of a run with a partner in another component that may reach the threshold; a row a member at most.

    A pair is looked at in the first band only that its slots share, so in one of its buckets.
    """
    bands, least = SLOTS // rows, least_agreement(percent)

    def kernel(t: pa.Table) -> pa.Table | None:
        comp = t.column("component").to_numpy()
        if (comp == comp[0]).all():
            return None
        n, own, band = t.column("n").to_numpy(), t.column("own").to_numpy(), t.column("band")[0].as_py()
        slots = np.frombuffer(b"".join(t.column("slots").to_pylist()), np.uint32).reshape(len(n), SLOTS)
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        left = np.flatnonzero(own == i)
        cols = left if i == j else np.flatnonzero(own == j)
        keep = np.zeros(len(n), bool)
        for r in left:
            c = cols[cols > r] if i == j else cols
            c = c[(comp[c] != comp[r]) & (100 * np.minimum(n[c], n[r]) >= percent * np.maximum(n[c], n[r]))]
            if len(c):
                same = slots[c] == slots[r]
                first = same[:, : bands * rows].reshape(len(c), bands, rows).all(2).argmax(1)
                c = c[(same.sum(1) >= least) & (first == band)]
                if len(c):
                    keep[r] = True
                    keep[c] = True
        return t.select(["bucket", "i", "j", "own", "id", "component"]).filter(pa.array(keep)) if keep.any() else None

    return kernel


def _linked(percent: int, columns: int = 1 << 14):
    """Edges of a run whose full sets are similar enough: exact intersections by blocks of shingles, given as stars."""

    def kernel(t: pa.Table) -> pa.Table | None:
        ids, comp, own = t.column("id").to_numpy(), t.column("component").to_numpy(), t.column("own").to_numpy()
        sets = [np.asarray(x.values) for x in t.column("shingles")]
        size = np.array([len(x) for x in sets])
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        left = np.flatnonzero(own == i)
        cols = left if i == j else np.flatnonzero(own == j)
        if not len(left) or not len(cols):
            return None
        every, at = np.unique(np.concatenate(sets), return_inverse=True)
        row = np.repeat(np.arange(len(ids)), size)
        common = np.bincount(at, minlength=len(every)) > 1
        place = np.cumsum(common) - 1
        row, at = row[common[at]], place[at[common[at]]]
        order = np.argsort(at, kind="stable")
        row, at = row[order], at[order]
        both = np.zeros((len(left), len(cols)), np.float32)
        for lo in range(0, int(common.sum()), columns):
            s, e = np.searchsorted(at, [lo, lo + columns])
            x = np.zeros((len(ids), columns), np.float32)
            x[row[s:e], at[s:e] - lo] = 1
            both += x[left] @ x[cols].T
        n = both.astype(np.int64)
        ok = (n * 100 >= (size[left][:, None] + size[cols][None, :] - n) * percent) & (comp[left][:, None] != comp[cols][None, :])
        x, y = np.nonzero(ok)
        if not len(x):
            return None
        u, v = star_edges(ids, left[x], cols[y])
        return pa.table({"a": pa.array(v, pa.int64()), "b": pa.array(u, pa.int64())})

    return kernel


def _judged(docs: DataFrame, words: int, percent: int, key: str, text: str) -> tuple[DataFrame, DataFrame]:
    """Rows (id, h, g, n, print) of docs, and of each print its component's first row as c0 (id, h, g).

    Every row has an identity of its own. Rows of one and the same set are a class, which is a node of the graph and
    has the number of its first row; so a key that several texts share names several nodes.
    """
    rows = band_rows(percent)
    body = F.coalesce(F.col(text), F.lit(""))
    slim = docs.select(F.col(key).cast("bigint").alias("id"), F.xxhash64(body).alias("h"), F.xxhash64(F.lit(1), body).alias("g"), F.col(text).alias("t"))
    made = slim.mapInArrow(_sketches(words, rows), "id bigint, h bigint, g bigint, n bigint, print binary, bands array<bigint>, slots binary")
    sketched = materialize(made.withColumn("row", F.monotonically_increasing_id()), "sketches")
    valid = sketched.filter("n > 0 AND id IS NOT NULL")
    first = valid.groupBy("print").agg(F.min(F.struct("id", "h", "g", "row")).alias("f"))
    classes = materialize(first.select("print", "f.id", "f.h", "f.g", F.col("f.row").alias("node")), "set-classes")
    own = valid.join(classes.select(F.col("node").alias("row")), "row", "left_semi").withColumn("id", F.col("row"))
    buckets = materialize(own.select("id", "n", F.posexplode("bands").alias("band", "bucket")), "buckets")
    node = F.struct("id", "n")
    drawn = F.struct(F.xxhash64("id", "bucket").alias("h"), "id", "n")
    centres = buckets.groupBy("bucket").agg(F.count("*").alias("members"), F.min(node).alias("c1"), F.min(drawn).alias("c2")).filter("members > 1")
    centres = materialize(centres.select("bucket", "members", "c1", F.struct("c2.id", "c2.n").alias("c2")), "centres")
    star = buckets.join(centres, "bucket").select("id", "n", F.explode(F.array("c1", "c2")).alias("c"))
    sized = lambda x, y: F.least(x, y) * 100 >= F.greatest(x, y) * percent
    pairs = star.filter((F.col("id") != F.col("c.id")) & sized(F.col("n"), F.col("c.n"))).select(F.least("id", "c.id").alias("a"), F.greatest("id", "c.id").alias("b"))
    pairs = materialize(pairs.distinct(), "star-pairs")
    links = materialize(_confirmed(pairs, classes, slim, words, percent), "links")
    found = materialize(connected_components(links), "components")

    # buckets that the stars leave in several components: every pair of two or three members was in a star already
    open_ = centres.filter((F.col("members") > 3) | ((F.col("members") == 3) & (F.col("c1.id") == F.col("c2.id")))).select("bucket")
    placed = buckets.join(open_, "bucket").join(found, F.col("id") == F.col("node"), "left").select("bucket", "band", "id", "n", F.coalesce("component", "id").alias("component"))
    placed = materialize(placed, "open-members")
    mixed = materialize(placed.groupBy("bucket").agg(F.count("*").alias("members"), F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi").select("bucket", "members"), "open-buckets")
    rest = placed.join(mixed, "bucket").join(own.select("id", "slots"), "id")
    tiled = over_runs(in_tiles(rest, "bucket", "members", "id", TILE), ["bucket", "i", "j"], _plausible(rows, percent), "bucket bigint, i int, j int, own int, id bigint, component bigint")
    tiled = materialize(tiled, "plausible")
    full = tiled.join(_full_sets(tiled.select(F.col("id").alias("c")), classes, slim, words), "id")
    full = full.repartition("bucket", "i", "j").sortWithinPartitions("bucket", "i", "j", "own", "id")
    more = materialize(over_runs(full, ["bucket", "i", "j"], _linked(percent), "a bigint, b bigint"), "links")
    final = materialize(connected_components(links.unionByName(more)), "components").withColumnRenamed("node", "v")

    placed = classes.join(final, classes["node"] == final["v"], "left").select("print", "id", "h", "g", F.coalesce("component", "node").alias("component"))
    placed = materialize(placed, "class-components")
    heads = materialize(placed.groupBy("component").agg(F.min(F.struct("id", "h", "g")).alias("c0")), "component-heads")
    return sketched.select("id", "h", "g", "n", "print"), placed.select("print", "component").join(heads, "component").select("print", "c0")


def near_groups(docs: DataFrame, words: int = 3, percent: int = 85, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_shingles, component_id, kept), one row for each row of docs.

    Documents with 100 * |intersection| >= percent * |union| are linked; component_id is the smallest key reachable.
    Null and empty texts and texts without words have an empty set and link with nothing. A null key links with
    nothing and has a null component. Rows that repeat a key are documents of their own: they are in one component only
    if their texts are linked. Empty tables give an empty result.
    """
    with passing("sketches", "class-components", "component-heads"):
        rows, heads = _judged(docs, words, percent, key, text)
    met = (F.col("n") > 0) & F.col("id").isNotNull()
    linked = rows.filter(met).join(heads, "print").select("id", "n", F.col("c0.id").alias("component_id"))
    alone = rows.filter(~met).select("id", "n", F.col("id").alias("component_id"))
    out = linked.unionByName(alone).select(F.col("id").alias(key), F.col("n").alias("n_shingles"), "component_id")
    return out.withColumn("kept", F.col(key).eqNullSafe(F.col("component_id")))


def drop_near_copies(docs: DataFrame, words: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of docs that stay, with their own columns: one row of each component, the one with the smallest key.

    Rows with a null key or an empty set all stay. Rows are told apart by key and text, so a key that several texts
    share loses only those that are copies; of rows that repeat both, one stays.
    """
    with passing("near-copies", "repeated-rows"):
        rows, heads = _judged(docs, words, percent, key, text)
        valid = rows.filter("n > 0 AND id IS NOT NULL").join(heads, "print")
        gone = valid.filter(F.struct("id", "h", "g") != F.col("c0")).select(F.col("id").alias("__k"), F.col("h").alias("__h"), F.col("g").alias("__g")).distinct()
        gone = materialize(gone, "near-copies")
        same = valid.filter(F.struct("id", "h", "g") == F.col("c0")).groupBy("id", "h", "g").agg(F.count("*").alias("times")).filter("times > 1")
        same = materialize(same.select(F.col("id").alias("__k"), F.col("h").alias("__h"), F.col("g").alias("__g")), "repeated-rows")
    body = F.coalesce(docs[text], F.lit(""))
    on = lambda t: (docs[key].cast("bigint") == t["__k"]) & (F.xxhash64(body) == t["__h"]) & (F.xxhash64(F.lit(1), body) == t["__g"])
    stay = docs.join(gone.hint("merge"), on(gone), "left_anti")  # one plan at every size
    if same.isEmpty():
        return stay
    once = docs.join(same, on(same), "left_semi").withColumn("__h", F.xxhash64(body)).dropDuplicates([key, "__h"]).drop("__h")
    return stay.join(same, on(same), "left_anti").unionByName(once)
