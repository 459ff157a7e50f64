"""SentencePiece encoding and decoding over a trie of distinct marked words.

A batch's distinct words, each marked with its leading blank, are sorted. Sorted order is the depth-first order of
their trie, and the forward table of a word is cut back to the prefix that it shares with the next one, so a prefix
is searched once for all words that have it. Encoded words stay in a bounded table of each task.

For a unigram model the forward table is Viterbi's: the best sum of piece scores up to each letter. For a BPE model
the sum of scores isn't what the library's merges give. There the forward table holds the last piece of each prefix's
encoding: the one piece that ends there and that merging leaves apart from the last piece before it, which is also a
function of the prefix alone; so the same traversal gives the merges' exact result. Words with runs of blanks, whose
merges all have one score, are merged directly.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLANK = "▁"
CACHE_WORDS, CACHE_LETTERS = 600_000, 48
_UNKNOWN_COST = 10.0


class PieceModel:
    """Pieces, scores and kinds of a model file; encoding and decoding of texts to ids and back."""

    def __init__(self, proto: bytes):
        from sentencepiece import sentencepiece_model_pb2 as pb

        m = pb.ModelProto()
        m.ParseFromString(proto)
        n = m.normalizer_spec
        if n.precompiled_charsmap or n.remove_extra_whitespaces or not n.escape_whitespaces:
            raise ValueError("only models that keep the text as it is are supported")
        self.dummy = n.add_dummy_prefix
        self.unigram = m.trainer_spec.model_type == 1
        self.fallback = m.trainer_spec.byte_fallback
        kind = m.SentencePiece
        self.text = [p.piece for p in m.pieces]
        self.kinds = [p.type for p in m.pieces]
        self.ids = {p.piece: i for i, p in enumerate(m.pieces) if p.type == kind.NORMAL}
        self.score = [p.score for p in m.pieces]
        if any(p.type == kind.USER_DEFINED for p in m.pieces):
            raise ValueError("models with pieces defined by users are not supported")
        self.unknown = next(i for i, p in enumerate(m.pieces) if p.type == kind.UNKNOWN)
        self.bytes = {int(p.piece[3:5], 16): i for i, p in enumerate(m.pieces) if p.type == kind.BYTE}
        # every end of a piece: looking back from a letter stops where no piece can end
        self.ends = {p[i:] for p in self.ids for i in range(len(p))}
        self.worst = min((self.score[i] for i in self.ids.values()), default=0.0) - _UNKNOWN_COST
        # blanks only lead pieces and no piece has a line end: then words can be encoded one by one
        self.parts = all(BLANK not in p.lstrip(BLANK) and "\n" not in p for p in self.ids)
        self.word = re.compile(f"{BLANK}*[^{BLANK}\n]+|{BLANK}+|\n+")
        self.known: dict[str, bytes] = {}
        self.apart: dict[tuple[int, int], bool] = {}

    # one word by merges: the library's rule, used for blanks and to tell which two pieces stay apart

    def merged(self, word: str) -> list[str]:
        """Symbols after all merges: always the best-scored adjacent pair that is a piece, the leftmost of equals."""
        sym: list[str | None] = list(word)
        n = len(sym)
        right, left = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[float, int, int, int]] = []

        def offer(i: int) -> None:
            if i >= 0 and (j := right[i]) < n and (p := self.ids.get(sym[i] + sym[j])) is not None:
                heapq.heappush(heap, (-self.score[p], i, j, len(sym[i]) + len(sym[j])))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, j, size = heapq.heappop(heap)
            if sym[i] is None or j >= n or sym[j] is None or right[i] != j or len(sym[i]) + len(sym[j]) != size:
                continue
            sym[i] += sym[j]
            sym[j] = None
            right[i] = right[j]
            if right[i] < n:
                left[right[i]] = i
            offer(left[i])
            offer(i)
        return [s for s in sym if s is not None]

    def stay_apart(self, a: int, b: int) -> bool:
        key = (a, b)
        if (found := self.apart.get(key)) is None:
            x, y = (self.text[a] if a >= 0 else ""), self.text[b]
            found = self.merged(x + y) == ([x, y] if x else [y])
            if len(self.apart) > 4_000_000:
                self.apart.clear()
            self.apart[key] = found
        return found

    def _extend(self, word: str, last: list[int], best: list[float]) -> None:
        """Fill the forward table from where it stands to the end of the word; last: id of the piece or -1 for unknown."""
        get, ends, apart = self.ids.get, self.ends, self.apart.get
        for e in range(len(last), len(word) + 1):
            s, found = e - 1, []
            while s >= 0 and (tail := word[s:e]) in ends:
                if (p := get(tail)) is not None:
                    found.append((s, p))
                s -= 1
            piece = -1
            if self.unigram:
                top = best[e - 1] + self.worst
                for s, p in found:
                    if (sum_ := best[s] + self.score[p]) > top:
                        top, piece = sum_, p
                best.append(top)
            else:
                for s, p in reversed(found):
                    before = last[s] if s else -1
                    ok = apart((before, p))
                    if self.stay_apart(before, p) if ok is None else ok:
                        piece = p
                        break
            last.append(piece)

    def _backward(self, word: str, last: list[int]) -> list[int]:
        out: list[int] = []
        e = len(word)
        while e:
            p = last[e]
            if p >= 0:
                out.append(p)
                e -= len(self.text[p])
            else:
                out += self._letter(word[e - 1])[::-1]
                e -= 1
        out.reverse()
        return out

    def _letter(self, c: str) -> list[int]:
        return [self.bytes[b] for b in c.encode("utf-8")] if self.fallback else [self.unknown]

    def _joined(self, ids: list[int]) -> list[int]:
        """Without byte fallback a run of unknown letters is one unknown piece."""
        return ids if self.fallback else [p for i, p in enumerate(ids) if p != self.unknown or not i or ids[i - 1] != p]

    def encode_words(self, words: list[str]) -> dict[str, list[int]]:
        """Ids of distinct words, by depth-first traversal of their trie."""
        out: dict[str, list[int]] = {}
        last, best, before = [-1], [0.0], ""
        for w in sorted(words):
            if not self.unigram and w.startswith(BLANK * 2):
                out[w] = self._joined([i for s in self.merged(w) for i in ([self.ids[s]] if s in self.ids else self._letter(s))])
                continue
            shared, most = 0, min(len(w), len(before))
            while shared < most and w[shared] == before[shared]:
                shared += 1
            del last[shared + 1 :], best[shared + 1 :]
            self._extend(w, last, best)
            out[w] = self._joined(self._backward(w, last))
            before = w
        return out

    def split(self, text: str) -> list[str]:
        if not text:
            return []
        marked = (BLANK if self.dummy else "") + text.replace(" ", BLANK)
        return self.word.findall(marked) if self.parts else [marked]

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        bags = [self.split(t) for t in texts]
        known = self.known
        new = {w for bag in bags for w in bag if w not in known}
        fresh = {w: np.array(i, "<u4").tobytes() for w, i in self.encode_words(list(new)).items()}
        both = {**fresh} if not known else None
        out = []
        for bag in bags:
            raw = b"".join([both[w] for w in bag] if both is not None else [fresh[w] if w in fresh else known[w] for w in bag])
            ids = np.frombuffer(raw, "<u4")
            if not self.fallback and len(ids):  # a run of unknown letters may span words
                ids = ids[~((ids == self.unknown) & np.r_[False, ids[:-1] == self.unknown])]
            out.append(ids)
        if len(known) + len(fresh) > CACHE_WORDS:
            known.clear()
        known.update((w, i) for w, i in fresh.items() if len(w) <= CACHE_LETTERS)
        return out

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids: pieces joined, bytes of fallback pieces as UTF-8, blanks back, the dummy prefix dropped."""
        if not hasattr(self, "_raw"):
            back = {i: b for b, i in self.bytes.items()}
            self._raw = [bytes([back[i]]) if i in back else (b" \xe2\x81\x87 " if k == 2 else b"" if k == 3 else t.replace(BLANK, " ").encode()) for i, (t, k) in enumerate(zip(self.text, self.kinds, strict=True))]
        text = b"".join([self._raw[i] for i in ids.tolist()]).decode("utf-8", "replace")
        return text[1:] if self.dummy and text.startswith(" ") else text


@lru_cache(1)
def _model(path: str) -> PieceModel:
    with open(path, "rb") as f:
        return PieceModel(f.read())


def encode_pieces(docs: DataFrame, model: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, pieces) of each row of docs: the ids of its whole text as the model's library gives them; null is empty.

    model: path of the .model file, which every executor has. Rows stay one by one; nothing is shuffled.
    """
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = _model(model)
        for b in batches:
            for s in range(0, b.num_rows, 256):
                part = b.slice(s, 256)
                ids = m.encode([t or "" for t in part.column(1).to_pylist()])
                offsets = np.r_[0, np.cumsum([len(x) for x in ids])].astype(np.int32)
                flat = np.concatenate([*ids, np.zeros(0, "<u4")]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], ["k", "pieces"])

    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(run, f"k {kind}, pieces array<int>").withColumnRenamed("k", key)


def decode_pieces(encoded: DataFrame, model: str, key: str = "doc_id", pieces: str = "pieces") -> DataFrame:
    """(key, text) of each row of encoded ids; null ids give an empty text."""
    kind = encoded.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = _model(model)
        for b in batches:
            texts = [m.decode(np.asarray(x.values if x.values is not None else [], np.int64)) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["k", "text"])

    return encoded.select(F.col(key).alias("k"), F.col(pieces).alias("p")).mapInArrow(run, f"k {kind}, text string").withColumnRenamed("k", key)


def piece_digests(docs: DataFrame, model: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, n_pieces, ids_crc32, round_trip) of each row: the encoding's digest and whether decoding gives the text back."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = _model(model)
        for b in batches:
            for s in range(0, b.num_rows, 1024):
                part = b.slice(s, 1024)
                texts = [t or "" for t in part.column(1).to_pylist()]
                ids = m.encode(texts)
                back = [m.decode(i) == t.replace(BLANK, " ") for i, t in zip(ids, texts, strict=True)]
                size = [len(t.encode("utf-8")) for t in texts]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(size, pa.int64()), pa.array([len(i) for i in ids], pa.int64()), pa.array([zlib.crc32(i.tobytes()) for i in ids], pa.int64()), pa.array(back, pa.bool_())],
                    ["k", "n_bytes", "n_pieces", "ids_crc32", "round_trip"],
                )

    out = docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(run, f"k {kind}, n_bytes bigint, n_pieces bigint, ids_crc32 bigint, round_trip boolean")
    return out.withColumnRenamed("k", key)
