"""Embedding near-dedup by sorted projection passes.

Each pass gives every vector a key of `depth` random hyperplane bits and compares all vectors of equal key, by exact
cosine in double precision, however many they are: rows are sorted by key, and a key held by more than a window of rows
is compared in tiles of a window each. The verified pairs of all passes are united. So whether a pass compares a pair
depends on the angle between the two alone, not on how many rows lie near them, and the number of passes that holds the
chance to miss a pair right at the threshold below MISS follows from the depth.

The depth is the one whose passes cost least by the number of rows that share keys, which probe passes of their own
planes measure on the table at hand. Vectors that crowd together share more bits, which makes shallow keys dear; where
no depth pays, it is 0: one pass that compares every pair. Then inside each component all members are compared in
tiles, which counts every link.

A run of rows writes at most one edge a vector (a star to the smallest id), never all pairs of a group. Rows of equal
vectors are one class, compared once however many they are; a class carries the number of its ids.
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

#: Rows of one side of a comparison: in passes, and when links are counted.
WINDOW, TILE = 1024, 256
#: Chance, for a pair exactly at the threshold, that no pass compares it.
MISS = 1e-4
#: Passes that only measure how many rows share keys, and the fewest rows a key should be left with.
PROBES, FEWEST = 4, 16
#: Bringing a row to a run costs as much as so many comparisons.
ROW_COST = 1_000
#: Rows of a partition aimed at.
PART_ROWS = 60_000


def _agree(threshold: float) -> float:
    """Chance that a random hyperplane leaves two vectors at the threshold on one side."""
    return 1 - math.acos(min(1.0, max(-1.0, threshold))) / math.pi


def passes_for(depth: int, threshold: float, miss: float = MISS) -> float:
    """Passes of `depth` bits needed, whatever the other vectors are; infinite where no number is enough."""
    hit = _agree(threshold) ** depth
    if not depth or not hit:
        return math.inf if depth else 1
    return math.ceil(math.log(miss) / math.log1p(-min(hit, 0.999)))


def depth_for(passes: int, threshold: float, deepest: int, miss: float = MISS) -> int:
    """The most bits, up to deepest, for which so many passes are enough."""
    return max(d for d in range(deepest + 1) if passes_for(d, threshold, miss) <= max(1, passes))


def _unit(column: pa.Array) -> list[np.ndarray | None]:
    """Vectors of length one, None where null, empty, zero or not finite throughout; single precision is kept as it is."""
    single = pa.types.is_float32(column.type.value_type)
    out = []
    for v in column:
        raw = None if v.values is None else v.values.to_numpy(zero_copy_only=False)
        x = None if raw is None else np.asarray(raw, np.float64)
        if x is None or not len(x) or not np.isfinite(x).all() or not x.any():
            out.append(None)
        elif single:  # doubles hold its squares, so tiles can norm it
            out.append(np.asarray(raw, np.float32))
        else:
            x = x / np.abs(x).max()
            out.append(x / float(np.sqrt(np.dot(x, x))))
    return out


def _planes(depth: int, dim: int, passes: int, seed: int) -> np.ndarray:
    return np.random.default_rng((seed, dim)).standard_normal((dim, passes * depth))


def _vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(id, h, print, vec): the vector's bytes, 4 or 8 a component, after a byte that says which, and what they are known by."""
    for b in batches:
        vecs = [None if u is None else bytes([u.itemsize]) + u.tobytes() for u in _unit(b.column(2))]
        prints = [None if v is None else hashlib.blake2b(v, digest_size=16).digest() for v in vecs]
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(prints, pa.binary()), pa.array(vecs, pa.binary())], ["id", "h", "print", "vec"])


def _keyed(passes: int, depth: int, seed: int):
    """(id, vec, keys): a key of `depth` bits for each pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes: dict[int, np.ndarray] = {}
        weights = (1 << np.arange(depth - 1, -1, -1)).astype(np.int64)
        for b in batches:
            if not b.num_rows:
                continue
            keys = np.zeros((b.num_rows, passes), np.int64)
            for at, x in _matrix(b.column(1)).values():
                dim = x.shape[1]
                if dim not in planes:
                    planes[dim] = _planes(depth, dim, passes, seed)
                keys[at] = (x @ planes[dim] > 0).reshape(len(at), passes, depth) @ weights
            ends = pa.array(np.arange(0, keys.size + 1, passes), pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.ListArray.from_arrays(ends, pa.array(keys.ravel()))], ["id", "vec", "keys"])

    return run


def _matrix(vecs: pa.ChunkedArray | pa.Array) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By dimension: the rows' places and the matrix of their vectors, of length one in double precision."""
    raw = vecs.to_pylist()
    out = {}
    kinds = np.array([len(v) * 16 + v[0] for v in raw])
    for kind in np.unique(kinds):
        at = np.flatnonzero(kinds == kind)
        dtype = np.float32 if kind % 16 == 4 else np.float64
        x = np.frombuffer(b"".join(raw[i][1:] for i in at), dtype).reshape(len(at), -1).astype(np.float64)
        if dtype is np.float32:
            x /= np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]
        dim = x.shape[1]
        out[dim] = (at, x) if dim not in out else (np.r_[out[dim][0], at], np.concatenate([out[dim][1], x]))
    return out


def _pairs(threshold: float):
    def kernel(t: pa.Table) -> pa.Table | None:
        all_ids, own = t.column("id").to_numpy(), t.column("own").to_numpy()
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        left, right = [], []
        for at, x in _matrix(t.column("vec")).values():
            ids, o = all_ids[at], own[at]
            a, b = np.flatnonzero(o == i), np.flatnonzero(o == j)
            u, v = np.nonzero(x[a] @ x[b].T >= threshold)
            u, v = a[u], b[v]
            if (u != v).any():
                near, root = star_edges(ids, u[u != v], v[u != v])
                left.append(near)
                right.append(root)
        return pa.table({"a": np.concatenate(left), "b": np.concatenate(right)}) if left else None

    return kernel


def _near(t: pa.Table, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, columns, which are linked) of a run, by dimension, every two different members of it once in each direction."""
    own = t.column("own").to_numpy()
    i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
    for at, x in _matrix(t.column("vec")).values():
        o = own[at]
        a, b = np.flatnonzero(o == i), np.flatnonzero(o == j)
        near = x[a] @ x[b].T >= threshold
        if i == j:
            np.fill_diagonal(near, False)
        yield at[a], at[b], near
        if i != j:
            yield at[b], at[a], near.T


def _links(threshold: float):
    """(id, n): the ids of the classes that a class is linked with, as far as a run shows; those of several classes aside."""

    def kernel(t: pa.Table) -> pa.Table | None:
        weight = t.column("weight").to_numpy()
        n = np.zeros(len(weight), np.int64)
        for a, b, near in _near(t, threshold):
            n[a] += near @ weight[b]
        return pa.table({"id": t.column("id"), "n": pa.array(n, pa.int64())})

    return kernel


def _shared_ids(threshold: float):
    """(id, other): the ids with several vectors that a class is linked with, as far as a run shows."""

    def kernel(t: pa.Table) -> pa.Table | None:
        node, shared = t.column("id").to_numpy(), t.column("shared").to_pylist()
        got = set()
        for a, b, near in _near(t, threshold):
            for c in np.flatnonzero([bool(shared[k]) for k in b]):
                got |= {(int(node[r]), other) for r in a[near[:, c]] for other in shared[b[c]]}
        if not got:
            return None
        x, y = zip(*got, strict=True)
        return pa.table({"id": pa.array(x, pa.int64()), "other": pa.array(y, pa.int64())})

    return kernel


def _plan(vectors: DataFrame, rows: int, threshold: float, window: int) -> tuple[int, int]:
    """(depth, passes) of the least cost: passes times what comparing all rows of equal keys costs, as probes measure it."""
    deepest = max(0, min(30, math.ceil(math.log2(max(1, rows) / FEWEST))))
    if not deepest:
        return 0, 1
    probes = vectors.mapInArrow(_keyed(PROBES, deepest, 20178), "id bigint, vec binary, keys array<bigint>")
    leaves = probes.select(F.posexplode("keys").alias("pass", "k")).groupBy("pass", "k").agg(F.count("*").alias("n"))
    levels = leaves.select("pass", "n", "k", F.explode(F.sequence(F.lit(0), F.lit(deepest))).alias("depth"))
    shared = levels.groupBy("pass", "depth", F.expr(f"shiftright(k, {deepest} - depth)").alias("k")).agg(F.sum("n").cast("double").alias("n"))
    cost = F.col("n") * (F.ceil(F.col("n") / window) * ROW_COST + F.col("n") / 2)
    spent = {r["depth"]: r["cost"] / PROBES for r in shared.groupBy("depth").agg(F.sum(cost).alias("cost")).collect()}
    depth = min(spent, key=lambda d: passes_for(d, threshold) * spent[d], default=0)
    return depth, int(passes_for(depth, threshold))


def _judged(vectors: DataFrame, threshold: float, key: str, vector: str, passes: int | None, window: int) -> tuple[DataFrame, DataFrame]:
    """Rows (id, h, print) of vectors, and of each print (n_links, component_id, head): head says that its class stays."""
    kind = "array<float>" if vectors.schema[vector].dataType.simpleString() == "array<float>" else "array<double>"
    v = F.col(vector).cast(kind)
    slim = vectors.select(F.col(key).cast("bigint").alias("id"), F.xxhash64(v).alias("h"), v.alias("v"))
    made = slim.mapInArrow(_vectors, "id bigint, h bigint, print binary, vec binary")
    units = materialize(made.withColumn("row", F.monotonically_increasing_id()), "unit-vectors")
    valid = units.filter("id IS NOT NULL AND vec IS NOT NULL")
    held = materialize(valid.groupBy("print", "id").agg(F.min("row").alias("row")), "class-ids")
    several = materialize(held.groupBy("id").agg(F.count("*").alias("times")).filter("times > 1").select("id"), "ids-of-several-vectors")
    classes = materialize(held.groupBy("print").agg(F.min("row").alias("node"), F.min("id").alias("rep"), F.count("*").alias("ids")), "vector-classes")
    first = classes.select(F.col("node").alias("row"))
    nodes = materialize(valid.join(first, "row", "left_semi").select(F.col("row").alias("id"), "vec"), "class-vectors")
    rows = nodes.count()
    if passes:
        depth = depth_for(passes, threshold, max(0, min(30, math.ceil(math.log2(max(1, rows) / FEWEST)))))
        passes = passes if depth else 1
    else:
        depth, passes = _plan(nodes, rows, threshold, window)
    keyed = materialize(nodes.mapInArrow(_keyed(passes, depth, 20177), "id bigint, vec binary, keys array<bigint>"), "projections")
    run = (F.col("pass").cast("bigint") * (1 << depth) + F.col("k")).alias("run")
    shared = materialize(keyed.select(F.posexplode("keys").alias("pass", "k")).select(run).groupBy("run").agg(F.count("*").alias("members")).filter("members > 1"), "shared-keys")
    # a row goes to the runs of keys that it shares with others only
    laid = keyed.select("id", "vec", F.posexplode("keys").alias("pass", "k")).select("id", "vec", run).join(shared, "run")
    edges = over_runs(in_tiles(laid, "run", "members", "id", window, max(1, rows * passes // PART_ROWS)), ["run", "i", "j"], _pairs(threshold), "a bigint, b bigint")
    found = materialize(connected_components(edges), "vector-components")
    sizes = materialize(found.groupBy("component").agg(F.count("*").alias("members")), "component-sizes")
    some_shared = not several.isEmpty()
    weights = classes.select(F.col("node").alias("id"), F.col("ids").alias("weight"))
    if some_shared:
        whose = held.join(several, "id").join(classes.select("print", "node"), "print").groupBy("node").agg(F.collect_set("id").alias("shared"))
        whose = materialize(whose.withColumnRenamed("node", "id"), "shared-ids")
        weights = weights.join(whose, "id", "left").withColumn("weight", F.col("weight") - F.coalesce(F.size("shared"), F.lit(0)))
    weights = materialize(weights, "class-weights")
    members = found.join(sizes, "component").withColumnRenamed("node", "id").join(nodes, "id").join(weights, "id")
    tiled = in_tiles(members, "component", "members", "id", TILE)
    counted = over_runs(tiled, ["component", "i", "j"], _links(threshold), "id bigint, n bigint").groupBy("id").agg(F.sum("n").alias("n"))
    # a class of its own is linked with itself, so far as it has more ids than one
    links = weights.join(counted, "id", "left").select("id", (F.col("weight") + F.coalesce("n", F.lit(0)) - 1).alias("n"))
    if some_shared:
        others = over_runs(tiled, ["component", "i", "j"], _shared_ids(threshold), "id bigint, other bigint")
        others = others.unionByName(whose.select("id", F.explode("shared").alias("other"))).distinct().groupBy("id").agg(F.count("*").alias("more"))
        links = links.join(others, "id", "left").select("id", (F.col("n") + F.coalesce("more", F.lit(0))).alias("n"))
    placed = classes.join(found.withColumnRenamed("node", "v"), F.col("node") == F.col("v"), "left").select("print", "node", "rep", F.coalesce("component", "node").alias("component"))
    placed = materialize(placed.join(links, F.col("node") == F.col("id")).select("print", "node", "rep", "component", "n"), "class-components")
    heads = materialize(placed.groupBy("component").agg(F.min(F.struct("rep", "node")).alias("f")).select("component", "f"), "component-heads")
    labels = placed.join(heads, "component").select("print", F.col("n").alias("n_links"), F.col("f.rep").alias("component_id"), (F.col("node") == F.col("f.node")).alias("head"))
    return units.select("id", "h", "print"), labels


def near_vectors(vectors: DataFrame, threshold: float = 0.9, key: str = "vec_id", vector: str = "embedding", passes: int | None = None, window: int = WINDOW) -> DataFrame:
    """(key, n_links, component_id, kept), one row for each row of vectors.

    n_links: other keys with a vector of cosine >= threshold; component_id: smallest key reachable by links, itself
    included. Null, empty, zero or non-finite vectors and those with null components link with nothing; vectors of
    different dimension neither. Rows that repeat a key are vectors of their own, linked only if alike, and never count
    as each other's link. A null key is left out of links and has a null component. Empty tables give an empty result.
    With `passes` the depth follows from their number.
    """
    with passing("unit-vectors", "class-components", "component-heads"):
        rows, labels = _judged(vectors, threshold, key, vector, passes, window)
    valid = F.col("id").isNotNull() & F.col("print").isNotNull()
    linked = rows.filter(valid).join(labels, "print").select("id", F.col("n_links").cast("bigint").alias("n_links"), "component_id")
    alone = rows.filter(~valid).select("id", F.lit(0).cast("bigint").alias("n_links"), F.col("id").alias("component_id"))
    out = linked.unionByName(alone).select(F.col("id").alias(key), "n_links", "component_id")
    return out.withColumn("kept", F.col(key).eqNullSafe(F.col("component_id")))


def drop_near_vectors(vectors: DataFrame, threshold: float = 0.9, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """The rows of vectors that stay, with their own columns: one of each component; rows that link with nothing all stay.

    Rows are told apart by key and vector; of rows that repeat both, one stays.
    """
    with passing("near-vectors", "repeated-rows"):
        rows, labels = _judged(vectors, threshold, key, vector, None, WINDOW)
        valid = rows.filter("id IS NOT NULL AND print IS NOT NULL").join(labels, "print")
        stays = F.col("head") & (F.col("id") == F.col("component_id"))
        named = [F.col("id").alias("__k"), F.col("h").alias("__h")]
        gone = materialize(valid.filter(~stays).select(*named).distinct(), "near-vectors")
        same = materialize(valid.filter(stays).groupBy("id", "h").agg(F.count("*").alias("times")).filter("times > 1").select(*named), "repeated-rows")
    kind = "array<float>" if vectors.schema[vector].dataType.simpleString() == "array<float>" else "array<double>"
    on = lambda t: (vectors[key].cast("bigint") == t["__k"]) & (F.xxhash64(vectors[vector].cast(kind)) == t["__h"])
    stay = vectors.join(gone, on(gone), "left_anti")
    if same.isEmpty():
        return stay
    once = stay.join(same, on(same), "left_semi").withColumn("__h", F.xxhash64(vectors[vector].cast(kind))).dropDuplicates([key, "__h"]).drop("__h")
    return stay.join(same, on(same), "left_anti").unionByName(once)
