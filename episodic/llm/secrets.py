"""Secret scans with corpus-wide ownership frequency.

Every text is scanned once for candidates: the three base kinds and short assigned values (kind `weak`). The hashes of
the candidates' values are counted over the whole corpus by distinct repositories (documents) and owners (sources). A
value that many owners hold is a widely copied example; one that few owners hold looks live, in however many documents
and copies they hold it. Base spans always stay;
weak ones are added only where their value is owner-specific and mixes letters and digits. Only the small candidate
rows are shuffled, never a text; the counts are hash aggregates with map-side combining, so a value that a third of
all rows hold is one row a task.

Null and empty texts have no spans. A null owner is an owner of its own. Rows are scanned and judged each for itself,
whatever keys they have, null or repeated; rows that repeat key and text count as one document.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import materialize, passing

KINDS = ("assign", "access", "hex", "weak")
# Fixed patterns and least lengths of the base kinds.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.A | re.I)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
ASSIGN_LEAST, ACCESS_LEAST = 12, 18
#: A weak value has at least so many letters; below ASSIGN_LEAST by its kind.
WEAK_LEAST = 6
#: A value held by more owners than this is a widely copied example.
COMMON_OWNERS = 3
_HINT = re.compile(r"[:=]")
#: What every text with a candidate matches, for the JVM: rows without it keep out of the join that cuts spans.
MAY_HOLD = "(?i:password|passwd|secret|token|api_?key)|AKIA|[0-9a-f]{16}"


def scan(text: str) -> list[tuple[int, int, int, str]]:
    """(start, end, kind number, value) of each candidate in order of start, then kind; offsets in code points."""
    found = []
    if _HINT.search(text):
        for m in ASSIGN.finditer(text):
            value = m[2]
            if len(value) >= ASSIGN_LEAST:
                found.append((m.start(), m.end(), 0, value))
            elif len(value) >= WEAK_LEAST and any(c.isdigit() for c in value) and any(c.isalpha() for c in value):
                found.append((m.start(), m.end(), 3, value))
    if "AKIA" in text:
        found += [(m.start(), m.end(), 1, m[0]) for m in ACCESS.finditer(text) if len(m[0]) >= ACCESS_LEAST]
    found += [(m.start(), m.end(), 2, m[0]) for m in HEX.finditer(text)]
    return sorted(found)


def _scan_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    span = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.int32()), ("value", pa.int64())])
    for b in batches:
        rows, digests = [], []
        for text in b.column(4):
            found = scan(text.as_py() or "")
            rows.append([{"start": s, "end": e, "kind": k, "value": xxhash.xxh3_64_intdigest(v) - (1 << 63)} for s, e, k, v in found])
            digests.append(hashlib.sha256(",".join(f"{KINDS[k]}:{s}:{e}" for s, e, k, _ in found if k < 3).encode()).hexdigest())
        yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(digests), pa.array(rows, pa.list_(span))], ["k", "owner", "h", "g", "base_sha256", "found"])


def _text_hashes(text):
    """Two hashes that tell the texts of one key apart."""
    body = F.coalesce(text, F.lit(""))
    return F.xxhash64(body), F.xxhash64(F.lit(1), body)


def candidates(docs: DataFrame, key: str = "doc_id", text: str = "text", owner: str = "source") -> DataFrame:
    """(row, k, owner, h, g, base_sha256, found) of each row; found lists all candidates with the hash of the value.

    row numbers the rows and h, g are hashes of the text: row is stable only once the table is written.
    """
    kind = docs.schema[key].dataType.simpleString()
    h, g = _text_hashes(F.col(text))
    plan = docs.select(F.col(key).alias("k"), F.col(owner).cast("string").alias("owner"), h.alias("h"), g.alias("g"), F.col(text).alias("t"))
    found = plan.mapInArrow(_scan_batches, f"k {kind}, owner string, h bigint, g bigint, base_sha256 string, found array<struct<start:int,end:int,kind:int,value:bigint>>")
    return found.withColumn("row", F.monotonically_increasing_id())


def ownership(found: DataFrame) -> DataFrame:
    """(value, n_docs, n_owners): in how many documents and with how many owners each candidate value occurs."""
    each = found.select("k", "h", "owner", F.explode("found.value").alias("value"))
    docs = each.groupBy("value", "owner", "k", "h").agg(F.lit(1).alias("one"))
    return docs.groupBy("value", "owner").agg(F.count("*").alias("n")).groupBy("value").agg(F.sum("n").alias("n_docs"), F.count("*").alias("n_owners"))


def _scanned(docs: DataFrame, key: str, text: str, owner: str, common_owners: int) -> DataFrame:
    """One row for each row of docs: k, h, g, base_sha256, spans_list."""
    found = materialize(candidates(docs, key, text, owner), "secret-candidates")
    held = materialize(ownership(found), "ownership")
    each = found.filter(F.size("found") > 0).select("row", F.explode("found").alias("c"))
    judged = each.join(held, each["c.value"] == held["value"]).select("row", "c", "n_docs", "n_owners", (F.col("n_owners") <= common_owners).alias("live"))
    kept = judged.filter((F.col("c.kind") < 3) | F.col("live"))
    span = F.struct(F.col("c.start").alias("start"), F.col("c.kind").alias("kind"), F.col("c.end").alias("end"), "n_docs", "n_owners", "live")
    lists = kept.groupBy("row").agg(F.array_sort(F.collect_list(span)).alias("spans_list"))
    none = F.array().cast(lists.schema["spans_list"].dataType)
    with_any = found.filter(F.size("found") > 0).join(lists, "row", "left")  # rows without a candidate need no join
    columns = ["k", "h", "g", "base_sha256", F.coalesce("spans_list", none).alias("spans_list")]
    return with_any.select(*columns).unionByName(found.filter(F.size("found") == 0).select("k", "h", "g", "base_sha256", none.alias("spans_list")))


def scan_secrets(docs: DataFrame, key: str = "doc_id", text: str = "text", owner: str = "source", common_owners: int = COMMON_OWNERS) -> DataFrame:
    """One row for each row of docs: key, base_sha256, spans_list (start, end, kind, n_docs, n_owners, live) sorted by start and kind."""
    return _scanned(docs, key, text, owner, common_owners).select(F.col("k").alias(key), "base_sha256", "spans_list")


def digest_columns(scanned: DataFrame, key: str = "doc_id") -> DataFrame:
    """Counts by kind and the spans as one string: kind:start:end, comma-joined, by start and then kind."""
    names = F.array(*map(F.lit, KINDS))
    one = lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))
    of = lambda k: F.size(F.filter("spans_list", lambda s: s["kind"] == k)).cast("bigint")
    return scanned.select(
        key, of(0).alias("n_assign"), of(1).alias("n_access"), of(2).alias("n_hex"), "base_sha256", F.array_join(F.transform("spans_list", one), ",").alias("spans"),
        F.size(F.filter("spans_list", lambda s: s["live"])).cast("bigint").alias("n_live"), F.size(F.filter("spans_list", lambda s: ~s["live"])).cast("bigint").alias("n_example"),
    )


def redact_live(docs: DataFrame, mark: str = "[REDACTED]", key: str = "doc_id", text: str = "text", owner: str = "source") -> DataFrame:
    """docs with every owner-specific span replaced by mark; widely copied examples stay; same columns, same rows.

    Spans find their rows by key and text, so each row loses its own spans only, whatever keys repeat or are null.
    """
    with passing("live-spans"):
        spans = _scanned(docs, key, text, owner, COMMON_OWNERS)
        live = spans.select(F.col("k").alias("__k"), F.col("h").alias("__h"), F.col("g").alias("__g"), F.filter("spans_list", lambda s: s["live"]).alias("__live"))
        live = materialize(live.filter(F.size("__live") > 0).dropDuplicates(["__k", "__h", "__g"]), "live-spans")
    h, g = _text_hashes(docs[text])
    may = F.coalesce(docs[text].rlike(MAY_HOLD), F.lit(False))
    joined = docs.filter(may).join(live, docs[key].eqNullSafe(live["__k"]) & (h == live["__h"]) & (g == live["__g"]), "left")
    cut = F.when(F.col("__live").isNull(), docs[text]).otherwise(_cut(text, mark))
    return joined.select(*[cut.alias(c) if c == text else docs[c] for c in docs.columns]).unionByName(docs.filter(~may))


def _cut(text: str, mark: str):
    """The text without its live spans, each replaced by mark; overlapping spans are replaced together."""
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))

    def step(acc, s):
        overlap = s["start"] < acc["at"]
        out = F.when(overlap, acc["out"]).otherwise(F.concat(acc["out"], F.substring(F.col(text), acc["at"] + 1, s["start"] - acc["at"]), F.lit(mark)))
        return F.struct(out.alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))

    return F.aggregate("__live", start, step, lambda acc: F.concat(acc["out"], F.substring(F.col(text), acc["at"] + 1, F.length(F.col(text)))))
