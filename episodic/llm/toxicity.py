"""Toxicity by maximum-scoring segments.

Token log-odds between toxic and clean documents, smoothed by a Dirichlet prior from the corpus, give each word a
score; a word that the lexicon lacks backs off to its first letters, and neutral words cost a little. One linear scan
finds every maximal scoring segment of a text. A segment's score becomes an expectation by extreme-value statistics
(decay from the clean score distribution, scale from clean documents), and the significant segments of a document add
up to one evidence value, which a one-variable logistic curve turns into a score.

The lexicon is learned from a bounded sample of labelled rows (SAMPLE of each class, by hash) and has a bounded number
of entries. The two calibrations are fitted on rows that the lexicon did not see: the sample is cut in two, and each
half is scored by the lexicon of the other. Scoring is one pass over whole texts without any shuffle.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .wordhash import LETTERS, spans, text_chunks, word_hashes

#: Labelled rows of each class to learn from, features of the lexicon, how sure a feature's log-odds must be, and how
#: large: common words whose odds differ a little are neutral, or a text that repeats one would gather them.
SAMPLE, LEXICON, SURE, LEAST_ODDS = 4_000, 20_000, 3.3, 3.0
#: Bytes of the prefixes that unknown words back off to, weight of the prior in documents, and cost of a neutral word.
PREFIXES, PRIOR, NEUTRAL = (5, 6, 7), 4.0, 0.15
#: Evidence beyond this says no more: one passage of forty nats is as sure as many.
MOST_EVIDENCE = 40.0
_TABLE = 1 << 20


@dataclass
class Lexicon:
    """Sorted feature hashes with log-odds and certainty; the statistics of clean text; the logistic curve."""

    keys: np.ndarray
    odds: np.ndarray
    sure: np.ndarray
    decay: float = 1.0
    scale: float = 0.1
    slope: float = 1.0
    offset: float = -3.0

    def __post_init__(self):
        self.maybe = np.zeros(_TABLE, bool)
        self.maybe[(self.keys & np.uint64(_TABLE - 1)).astype(np.int64)] = True

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(places in h, places in the lexicon) of the hashes that it has."""
        at = np.flatnonzero(self.maybe[(h & np.uint64(_TABLE - 1)).astype(np.int64)])
        if not len(at) or not len(self.keys):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        i = np.minimum(np.searchsorted(self.keys, h[at]), len(self.keys) - 1)
        ok = self.keys[i] == h[at]
        return at[ok], i[ok]

    def scores(self, word: np.ndarray, heads: dict[int, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """(places, log-odds) of the words that have any; the surest of a word's features counts."""
        place, entry = [], []
        for h in (word, *heads.values()):
            p, e = self.find(h)
            place.append(p)
            entry.append(e)
        p, e = np.concatenate(place), np.concatenate(entry)
        order = np.lexsort((-self.sure[e], p))
        p, e = p[order], e[order]
        first = np.r_[True, p[1:] != p[:-1]] if len(p) else np.zeros(0, bool)
        return p[first], self.odds[e[first]]


def maximal_segments(places: np.ndarray, scores: np.ndarray, neutral: float = NEUTRAL) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (first place, last place, score), in one pass over the scored places.

    Places between two scored ones cost `neutral` each. Every candidate keeps the running totals at its two ends; a new
    one absorbs those back to the nearest whose left total is lower, if its right total is lower too.
    """
    total, last = 0.0, -1
    held: list[tuple[int, int, float, float]] = []  # first, last, total before, total after
    for at, s in zip(places.tolist(), scores.tolist(), strict=True):
        total -= neutral * (at - last - 1) if last >= 0 else 0.0
        before, total, last = total, total + s, at
        if s <= 0:
            continue
        first, low, high = at, before, total
        while True:
            j = len(held) - 1
            while j >= 0 and held[j][2] >= low:
                j -= 1
            if j < 0 or held[j][3] >= high:
                held.append((first, at, low, high))
                break
            first, low = held[j][0], held[j][2]
            del held[j:]
    return [(a, b, high - low) for a, b, low, high in held]


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(feature, half, toxic documents, clean documents) of each batch; a document counts once for a feature."""
    for b in batches:
        group = b.column(1).to_numpy() * 2 + b.column(2).to_numpy()  # label and half
        got: dict[int, list[np.ndarray]] = {g: [] for g in range(4)}
        for first, last, data, off in text_chunks(b.column(0)):
            starts, ends, at = spans(data, off, LETTERS)
            word, heads = word_hashes(data, starts, ends, PREFIXES)
            for r in range(last - first):
                w = slice(at[r], at[r + 1])
                own = np.unique(np.concatenate([word[w], *(h[w] for h in heads.values())]))
                got[int(group[first + r])].append(own[own != 0])
        for half in (0, 1):
            every = np.concatenate([*got[half], *got[2 + half], np.zeros(0, np.uint64)])
            y = np.repeat([0, 1], [sum(map(len, got[half])), sum(map(len, got[2 + half]))])
            keys, inv = np.unique(every, return_inverse=True)
            toxic = np.bincount(inv, y, len(keys)).astype(np.int64)
            both = np.bincount(inv, minlength=len(keys))
            yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(np.full(len(keys), half), pa.int32()), pa.array(toxic), pa.array(both - toxic)], ["f", "half", "y1", "y0"])


def _sample(docs: DataFrame, labels: DataFrame, key: str, text: str, label: str, most: int) -> DataFrame:
    """At most `most` labelled documents of each class, those with the smallest hashes, each in one half; both tables are read once."""
    own = labels.filter(F.col(label).isin(0, 1) & F.col(key).isNotNull()).select(F.col(key).alias("k"), F.col(label).cast("int").alias("y"), F.xxhash64(key).alias("h"))
    drawn = [own.filter(F.col("y") == y).orderBy("h", "k").limit(most) for y in (0, 1)]
    half = F.pmod(F.shiftright("h", 7), F.lit(2)).cast("int")
    chosen = F.broadcast(drawn[0].unionByName(drawn[1]).select("k", "y", half.alias("half")))  # 2 * most rows at most
    return docs.join(chosen, docs[key] == chosen["k"]).select(F.coalesce(F.col(text), F.lit("")).alias("t"), "y", "half")


def _lexicon(counts: DataFrame, n1: int, n0: int) -> Lexicon:
    """The surest features by log-odds with a Dirichlet prior, from (f, y1, y0); one document more or less decides none."""
    if not n1 or not n0:
        return Lexicon(np.zeros(0, np.uint64), np.zeros(0), np.zeros(0))
    prior = PRIOR * (F.col("y1") + F.col("y0")) / F.lit(n1 + n0) + 0.5
    side = lambda y, n: F.log((F.col(y) + prior) / (F.lit(n + PRIOR + 1) - F.col(y) - prior))
    odds = side("y1", n1) - side("y0", n0)
    sure = odds / F.sqrt(1 / (F.col("y1") + prior) + 1 / (F.col("y0") + prior))
    top = counts.filter("y1 + y0 >= 5").select("f", odds.alias("odds"), sure.alias("sure")).filter((F.abs("sure") >= SURE) & (F.abs("odds") >= LEAST_ODDS))
    rows = top.orderBy(F.desc(F.abs("sure")), "f").limit(LEXICON).toPandas()
    rows = rows.assign(f=rows["f"].to_numpy(np.int64).view(np.uint64)).sort_values("f")
    return Lexicon(rows["f"].to_numpy(np.uint64), rows["odds"].to_numpy(float), np.abs(rows["sure"].to_numpy(float)))


def learn(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", sample: int = SAMPLE) -> Lexicon:
    """The lexicon and its calibrations from labelled rows; without rows of both classes an empty lexicon.

    Rows whose label is null or neither 0 nor 1, or whose key is null, teach nothing.
    """
    drawn = _sample(docs, labels, key, text, label, sample).persist()
    counts = drawn.mapInArrow(_features, "f bigint, half int, y1 bigint, y0 bigint").groupBy("f", "half").agg(F.sum("y1").alias("y1"), F.sum("y0").alias("y0")).persist()
    try:
        size = {(r["y"], r["half"]): r["n"] for r in drawn.groupBy("y", "half").agg(F.count("*").alias("n")).collect()}
        n = [[size.get((y, half), 0) for half in (0, 1)] for y in (0, 1)]
        lex = _lexicon(counts.groupBy("f").agg(F.sum("y1").alias("y1"), F.sum("y0").alias("y0")), sum(n[1]), sum(n[0]))
        if not sum(n[1]) or not sum(n[0]):
            return lex
        halves = [_lexicon(counts.filter(F.col("half") == half), n[1][half], n[0][half]) for half in (0, 1)]
        _calibrate(lex, halves, drawn)
        true = labels.filter(F.col(label).isin(0, 1)).groupBy(F.col(label).alias("y")).agg(F.count("*").alias("n")).collect()
        _curve(lex, halves, drawn, {r["y"]: r["n"] for r in true})
        return lex
    finally:
        drawn.unpersist()
        counts.unpersist()


def _unseen(halves: list[Lexicon], b: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(label, words, scored places, log-odds) of each row (text, label, half), by the lexicon of the other half."""
    for half in (0, 1):
        own = b.filter(pa.array(b.column(2).to_numpy() == half))
        for y, (w, p, s) in zip(own.column(1).to_pylist(), _documents(halves[1 - half], own.column(0)), strict=True):
            yield y, w, p, s


def _calibrate(lex: Lexicon, halves: list[Lexicon], drawn: DataFrame) -> None:
    """Decay: the positive root of the mean of exp(decay * score) = 1 over clean words. Scale: fits clean maxima."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = list(_unseen(halves, b))
            hits = np.concatenate([s for *_, s in rows]) if rows else np.zeros(0)
            value, n = np.unique(np.round(hits, 2), return_counts=True)
            best = [max((x[2] for x in maximal_segments(p, s)), default=0.0) for _, _, p, s in rows]
            words = [w for _, w, _, _ in rows]
            yield pa.RecordBatch.from_arrays(
                [pa.array([*value, 0.0] + best, pa.float64()), pa.array([*n, sum(words) - len(hits)] + words, pa.int64()), pa.array([0] * (len(value) + 1) + [1] * len(best), pa.int32())], ["v", "n", "kind"]
            )

    clean = drawn.filter("y = 0").mapInArrow(run, "v double, n bigint, kind int")
    got = clean.filter("kind = 0").groupBy("v").agg(F.sum("n").alias("n")).toPandas()  # scores rounded to hundredths: a few thousand
    v = np.where(got["v"] == 0, -NEUTRAL, got["v"]).astype(float)
    w = got["n"].to_numpy(float) / max(1.0, got["n"].sum())
    lo, hi = 1e-3, 20.0
    if len(v) and v.max() > 0 and (v * w).sum() < 0:
        while hi - lo > 1e-6:
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if (w * np.exp(np.minimum(mid * v, 700))).sum() < 1 else (lo, mid)
        lex.decay = min(max(lo, 0.05), 5.0)
    fit = clean.filter("kind = 1").agg(F.count("*"), F.sum(F.col("n") * F.exp(-F.col("v") * lex.decay))).first()
    lex.scale = max(1e-6, fit[0] / fit[1]) if fit[1] else 0.1


def _curve(lex: Lexicon, halves: list[Lexicon], drawn: DataFrame, true: dict[int, int]) -> None:
    """Logistic regression of the label on the evidence, with the classes weighted as all labelled rows have them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [(evidence(lex, w, maximal_segments(p, s))[0], y) for y, w, p, s in _unseen(halves, b)]
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in rows], pa.float64()), pa.array([y for _, y in rows], pa.int32())], ["x", "y"])

    got = drawn.mapInArrow(run, "x double, y int").toPandas()  # 2 * SAMPLE rows at most
    x, y = np.minimum(got["x"].to_numpy(float), MOST_EVIDENCE), got["y"].to_numpy(float)
    w = np.where(y == 1, true.get(1, 1) / max(1.0, y.sum()), true.get(0, 1) / max(1.0, (1 - y).sum()))
    w, a, b = w / w.mean(), 0.0, 0.0
    for _ in range(60):
        p = 1 / (1 + np.exp(-(a * x + b)))
        g = np.array([(w * (y - p) * x).sum() - 0.1 * a, (w * (y - p)).sum()])
        r = w * p * (1 - p)
        h = np.array([[(r * x * x).sum() + 0.1, (r * x).sum()], [(r * x).sum(), r.sum() + 1e-9]])
        step = np.linalg.solve(h, g)
        step *= min(1.0, 2.0 / max(1e-12, np.abs(step).max()))
        a, b = a + step[0], b + step[1]
    lex.slope, lex.offset = max(a, 1e-3), b


def _documents(lex: Lexicon, texts: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(words, scored places, log-odds) of each text."""
    for w, p, s, _, _ in _located(lex, texts):
        yield w, p, s


def _located(lex: Lexicon, texts: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """As _documents, with the byte offsets in the text where each scored word starts and ends."""
    for first, last, data, off in text_chunks(texts):
        starts, ends, at = spans(data, off, LETTERS)
        word, heads = word_hashes(data, starts, ends, PREFIXES)
        p, s = lex.scores(word, heads)
        cut = np.searchsorted(p, at)
        for r in range(last - first):
            own = slice(cut[r], cut[r + 1])
            yield int(at[r + 1] - at[r]), p[own] - at[r], s[own], starts[p[own]] - off[r], ends[p[own]] - off[r]


def evidence(lex: Lexicon, words: int, segments: list[tuple[int, int, float]]) -> tuple[float, list[tuple[int, int, float, float]]]:
    """The summed surprise of the significant segments and these with their expectations (below 1 in clean text)."""
    out, total = [], 0.0
    for a, b, s in segments:
        e = lex.scale * words * math.exp(-lex.decay * s)
        if e < 1:
            out.append((a, b, s, e))
            total -= math.log(max(e, 1e-300))
    return total, out


def score_texts(docs: DataFrame, lex: Lexicon, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, score, predicted, n_passages, passages) of each row of docs; only the text is an input.

    passages: every significant segment as (start, end, score, expectation), offsets in UTF-8 bytes. Null and empty
    texts have no passage and the score of no evidence.
    """
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        item = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64()), ("expectation", pa.float64())])
        for b in batches:
            scores, passages = [], []
            for words, p, s, starts, ends in _located(lex, b.column(1)):
                x, found = evidence(lex, words, maximal_segments(p, s)) if (s > 0).any() else (0.0, [])
                scores.append(1 / (1 + math.exp(-min(700.0, max(-700.0, lex.slope * min(x, MOST_EVIDENCE) + lex.offset)))))
                passages.append([{"start": int(starts[np.searchsorted(p, a)]), "end": int(ends[np.searchsorted(p, z)]), "score": v, "expectation": e} for a, z, v, e in found])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(scores, pa.float64()), pa.array(passages, pa.list_(item))], ["k", "score", "passages"])

    out = docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(run, f"k {kind}, score double, passages array<struct<start:bigint,end:bigint,score:double,expectation:double>>")
    return out.select(F.col("k").alias(key), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.size("passages").cast("bigint").alias("n_passages"), "passages")
