"""Token counts by rank-synchronous array merging.

The distinct pre-tokens of a batch become one ragged numpy array of symbol ids. In every round each sequence finds the
lowest merge rank among its adjacent pairs and replaces all occurrences of that pair, left to right, at once; sequences
without a mergeable pair leave. The surviving symbols are the tokens. Counts of words are kept in a bounded table of
each task, so a word is merged about once a task, and a document's count is the sum over its words.

The text is prepared as the vocabulary file says: special strings cut out first (one token each), NFC, lower case,
white space dropped, the split pattern of the file. Null and empty texts have 0 tokens; no prefix or truncation.
"""

from __future__ import annotations

import json
import unicodedata
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Words kept by a task with their counts, and letters of the longest word that is kept.
CACHE_WORDS, CACHE_LETTERS = 1_000_000, 64
_NONE = np.int64(1 << 40)


class RankMerger:
    """The vocabulary file of a word-end BPE tokenizer as sorted arrays of pair keys, ranks and results."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        model, vocab = spec["model"], spec["model"]["vocab"]
        self.end = model.get("end_of_word_suffix") or ""
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        key = np.array([(vocab[a] << 32) | vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(key, kind="stable")
        self.key, self.rank = key[order], order.astype(np.int64)
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        letters = _byte_letters()
        self.plain = np.array([vocab[c] for c in letters], np.int64)
        self.last = np.array([vocab[c + self.end] for c in letters], np.int64)
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        split = next((p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split"), r"\S+")
        self.split = regex.compile(split.replace(r"\s", r"\p{White_Space}"))
        self.known: dict[str, int] = {}
        self.newer = _newer_capitals()

    def prepare(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")
        return text.lower()

    def words(self, text: str) -> tuple[list[str], int]:
        """The pre-tokens of a text and the number of special strings in it."""
        if self.special is None or "<|" not in text:
            return self.split.findall(self.prepare(text)), 0
        parts, at, n = [], 0, 0
        for m in self.special.finditer(text):
            parts += self.split.findall(self.prepare(text[at : m.start()]))
            at, n = m.end(), n + 1
        return parts + self.split.findall(self.prepare(text[at:])), n

    def merge(self, words: list[str]) -> np.ndarray:
        """Surviving symbols of each word."""
        raw = [(w if w.isascii() else w.translate(self.newer)).encode("utf-8") for w in words]
        sizes = np.array([len(b) for b in raw], np.int64)
        data = np.frombuffer(b"".join(raw), np.uint8)
        ends = np.cumsum(sizes)
        sym = self.plain[data]
        sym[ends - 1] = self.last[data[ends - 1]]
        seq = np.repeat(np.arange(len(raw)), sizes)
        out = np.zeros(len(raw), np.int64)
        while len(sym):
            same = seq[1:] == seq[:-1]
            key = (sym[:-1] << 32) | sym[1:]
            at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
            rank = np.where(same & (self.key[at] == key), self.rank[at], _NONE)
            first = np.flatnonzero(np.r_[True, ~same])
            best = np.minimum.reduceat(np.r_[rank, _NONE], first)
            size = np.diff(np.r_[first, len(sym)])
            done = best >= _NONE
            out[seq[first[done]]] = size[done]
            hit = (rank < _NONE) & (rank == np.repeat(best, size)[:-1])
            where = np.flatnonzero(hit)
            if len(where) > 1:  # of overlapping hits (a run of one symbol) every second one, from the left
                run = np.flatnonzero(np.r_[True, np.diff(where) != 1])
                nth = np.arange(len(where)) - np.repeat(run, np.diff(np.r_[run, len(where)]))
                where = where[nth % 2 == 0]
            sym[where] = self.made[rank[where]]
            stay = np.repeat(~done, size)
            stay[where + 1] = False
            sym, seq = sym[stay], seq[stay]
        return out

    def counts(self, texts: list[str]) -> list[int]:
        bags, specials = [], []
        for t in texts:
            w, n = self.words(t)
            bags.append(Counter(w))
            specials.append(n)
        new = list({w for bag in bags for w in bag if w not in self.known})
        fresh = dict(zip(new, map(int, self.merge(new)), strict=True)) if new else {}
        known = self.known
        out = []
        for bag, n in zip(bags, specials, strict=True):
            for w, k in bag.items():
                c = known.get(w)
                n += k * (fresh[w] if c is None else c)
            out.append(n)
        if len(known) + len(fresh) > CACHE_WORDS:
            known.clear()
        known.update((w, c) for w, c in fresh.items() if len(w) <= CACHE_LETTERS)
        return out


def _byte_letters() -> list[str]:
    """The printable letter that byte-level vocabularies use for each byte: itself if printable, else the next from 256."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(spare)) for b in range(256)]


@lru_cache(1)
def _newer_capitals() -> dict[int, str]:
    """Capitals that the library's Unicode tables have and Python's lack, with their small letters."""
    from tokenizers import normalizers

    unknown = [chr(c) for c in range(128, 0x20000) if unicodedata.category(chr(c)) == "Cn"]
    small = normalizers.Lowercase().normalize_str("\n".join(unknown)).split("\n")
    return {ord(c): s for c, s in zip(unknown, small, strict=True) if c != s}


@lru_cache(1)
def _merger(path: str) -> RankMerger:
    return RankMerger(path)


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 2048, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, n_bytes, n_tokens, over_limit) of each row of docs, one row for each, repeated rows too.

    vocabulary: path of a word-end BPE file that every executor has. Null text counts as empty: 0 bytes, 0 tokens.
    """
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = _merger(vocabulary)
        for b in batches:
            n = []
            values = b.column(1)
            for i in range(0, len(values), 256):
                n += m.counts([t or "" for t in values.slice(i, 256).to_pylist()])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(n, pa.int64())], ["k", "n_bytes", "n_tokens"])

    plan = docs.select(F.col(key).alias("k"), F.col(text).alias("t"), F.coalesce(F.octet_length(text), F.lit(0)).cast("bigint").alias("n_bytes"))
    out = plan.mapInArrow(run, f"k {kind}, n_bytes bigint, n_tokens bigint")
    return out.select(F.col("k").alias(key), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
