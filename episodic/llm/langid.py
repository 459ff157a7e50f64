"""Language ID by rank-order n-gram profiles.

A profile lists the most frequent letter n-grams (1 to 3, words padded with a blank) of a language in order. A document
gets its own profile from its whole text, and the distance to a language is the sum over the document's n-grams of how
far each is out of place there, with a fixed penalty for one that is missing. The nearest language wins.

Profiles come from a bounded sample of labelled rows; scoring is one pass of vectorised sorting over Arrow batches,
with no shuffle. The profiles are a fixed number of n-grams for each language, so what is broadcast doesn't grow.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Labelled rows of each language that profiles are learned from at most (smallest hash first), and letters of each.
SAMPLE_DOCS = 2_000
#: N-grams of a profile.
PROFILE = 400
_BITS, _BLANK = 21, np.uint64(1)


@lru_cache(1)
def _letters() -> np.ndarray:
    """Code point to its lower-case code point if a letter, else 0; lower-casing that gives several keeps the first."""
    table = np.zeros(sys.maxunicode + 1, np.uint32)
    for c in range(sys.maxunicode + 1):
        s = chr(c)
        if s.isalpha():
            table[c] = ord(s.lower()[0])
    return table


def ranked_ngrams(text: str, most: int) -> tuple[np.ndarray, np.ndarray]:
    """The most frequent n-grams of the text as integers, with counts; frequent first, ties by n-gram."""
    codes = _letters()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
    padded = np.zeros(len(codes) + 2, np.uint32)
    padded[1:-1] = codes
    inside = padded > 0
    if not inside.any():
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    keep = inside.copy()  # of a run of other characters one blank stays on either side of a word
    keep[:-1] |= inside[1:]
    keep[1:] |= inside[:-1]
    gap = keep & ~inside
    keep[1:] &= ~(gap[1:] & gap[:-1])
    seq = padded[keep].astype(np.uint64)
    seq[seq == 0] = _BLANK
    b = np.uint64(_BITS)
    two = (seq[:-1] << b) | seq[1:]
    three = (two[:-1] << b) | seq[2:]
    middle = seq[1:-1] != _BLANK if len(seq) > 2 else np.zeros(0, bool)
    grams = np.concatenate([seq[seq != _BLANK], two, three[middle]])
    grams.sort()
    first = np.flatnonzero(np.r_[True, grams[1:] != grams[:-1]])
    n = np.diff(np.r_[first, len(grams)])
    if len(n) > most:
        least = np.partition(n, len(n) - most)[len(n) - most]
        first, n = first[n >= least], n[n >= least]
    order = np.argsort(-n, kind="stable")[:most]
    return grams[first[order]], n[order]


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """N-gram counts of each language in a batch, those of whole texts."""
    for b in batches:
        sums: dict[str, dict[int, int]] = {}
        for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            own = sums.setdefault(lang, {})
            for g, n in zip(*map(np.ndarray.tolist, ranked_ngrams(text or "", 1 << 30)), strict=True):
                own[g] = own.get(g, 0) + n
        rows = [(lang, g, n) for lang, own in sums.items() for g, n in own.items()]
        cols = list(zip(*rows, strict=True)) or [[], [], []]
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64())], ["lang", "gram", "n"])


def learn_profiles(docs: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", sample: int = SAMPLE_DOCS, size: int = PROFILE) -> dict[str, list[int]]:
    """The ranked n-grams of each language from at most `sample` labelled rows of it; null languages and texts are left out."""
    from pyspark.sql import Window

    labelled = docs.filter(F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("t"), F.xxhash64(key).alias("h"))
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    # thin out by hash first so that what is ranked is small, then take exactly the smallest hashes
    chance = F.create_map(*[x for k, n in sizes.items() for x in (F.lit(k), F.lit(min(1.0, 1.5 * sample / n)))]) if sizes else None
    if not sizes:
        return {}
    thin = labelled.filter(F.pmod("h", F.lit(1 << 40)) / F.lit(float(1 << 40)) < chance[F.col("lang")])
    drawn = thin.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.pmod("h", F.lit(1 << 40)), "h"))).filter(F.col("r") <= sample)
    counted = drawn.select("lang", "t").mapInArrow(_counts, "lang string, gram bigint, n bigint").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    top = counted.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))).filter(F.col("r") <= size)
    out: dict[str, list[int]] = {}
    for r in sorted(top.select("lang", "gram", "r").collect(), key=lambda r: (r["lang"], r["r"])):
        out.setdefault(r["lang"], []).append(r["gram"])
    return out


class Profiles:
    """Sorted n-grams of all profiles with the place of each in every language."""

    def __init__(self, profiles: dict[str, list[int]], size: int):
        self.names = sorted(profiles)
        self.size = size
        self.grams = np.unique(np.array([g for p in profiles.values() for g in p], np.uint64))
        self.place = np.full((len(self.grams) + 1, len(self.names)), -1, np.int64)
        for j, lang in enumerate(self.names):
            at = np.searchsorted(self.grams, np.array(profiles[lang], np.uint64))
            self.place[at, j] = np.arange(len(profiles[lang]))

    def predict(self, text: str | None) -> tuple[str, float]:
        grams, _ = ranked_ngrams(text or "", self.size)
        if not len(grams) or not self.names:
            return "und", 0.0
        at = np.minimum(np.searchsorted(self.grams, grams), len(self.grams) - 1)
        at[self.grams[at] != grams] = len(self.grams)
        there = self.place[at]
        mine = np.arange(len(grams))[:, None]
        away = np.where(there < 0, self.size, np.abs(there - mine)).sum(0) / (self.size * len(grams))
        best = int(np.argmin(away))
        rest = np.delete(away, best)
        lead = float(rest.min() - away[best]) if len(rest) else float(1 - away[best])
        return self.names[best], min(1.0, max(0.0, 1.0 - float(away[best])) * 0.5 + min(0.5, 2.5 * lead))


def language_of(profiles: dict[str, list[int]], size: int = PROFILE):
    """A function of a text column that gives struct<lang_pred, score>; the row's other columns stay in the JVM."""

    @F.arrow_udf("lang_pred string, score double")
    def said(texts: pa.Array) -> pa.Array:
        model = Profiles(profiles, size)
        found = [model.predict(t.as_py()) for t in texts]
        return pa.StructArray.from_arrays([pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], ["lang_pred", "score"])

    return said


def has_letter():
    """A function of a text column: whether the text has a letter, as n-grams count letters; false for null."""

    @F.arrow_udf("boolean")
    def said(texts: pa.Array) -> pa.Array:
        return pa.array([any(map(str.isalpha, t.as_py() or "")) for t in texts], pa.bool_())

    return said


def detect(docs: DataFrame, profiles: dict[str, list[int]], text: str = "text", key: str = "doc_id", size: int = PROFILE) -> DataFrame:
    """(key, lang_pred, score) of each row: the nearest language of the whole text; `und` with score 0 where it has no letter.

    The score grows with closeness and with the lead over the next language. Ties go to the first name in order.
    """
    return docs.select(F.col(key), language_of(profiles, size)(F.col(text)).alias("said")).select(key, "said.lang_pred", "said.score")
