"""Vectorised words over Arrow string batches: spans, 64-bit hashes and prefix hashes, without a Python loop a word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

CHUNK_BYTES = 4 << 20
LONG_WORD = 64
_MULT = np.uint64(0x9E3779B97F4A7C15)

WHITE = np.zeros(256, bool)
WHITE[[0x20, *range(0x09, 0x0E)]] = True
NOT_WHITE = ~WHITE

LETTERS = np.zeros(256, bool)
LETTERS[ord("A") : ord("Z") + 1] = True
LETTERS[ord("a") : ord("z") + 1] = True
LETTERS[128:] = True

LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def mix(h: np.ndarray) -> np.ndarray:
    """A finalizer that spreads every input bit over the 64 output bits."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def text_chunks(texts: pa.Array, most: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets from 0) of runs of whole rows; a null row is empty; one long row is one run."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_string()).fill_null("")
    if not len(texts):
        return
    _, off, data = texts.buffers()
    off = np.frombuffer(off, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    row = 0
    while row < len(texts):
        end = max(row + 1, int(np.searchsorted(off, off[row] + most, "right")) - 1)
        yield row, end, data[off[row] : off[end]], off[row : end + 1] - off[row]
        row = end


def spans(data: np.ndarray, offsets: np.ndarray, member: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of member bytes that stay inside one row, and the first word of each row."""
    inside = member[data]
    edge = np.empty(len(data) + 1, bool)
    edge[0], edge[-1] = True, True
    edge[1:-1] = inside[1:] != inside[:-1]
    edge[offsets] = True
    cut = np.flatnonzero(edge)
    starts, ends = cut[:-1], cut[1:]
    keep = inside[starts] if len(starts) else np.zeros(0, bool)
    starts, ends = starts[keep], ends[keep]
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, prefixes: tuple[int, ...] = ()) -> tuple[np.ndarray, dict[int, np.ndarray]]:
    """64-bit hashes of the lower-cased words; for each length in prefixes those of the words' first bytes (0 if shorter)."""
    length = ends - starts
    order = np.argsort(-np.minimum(length, LONG_WORD + 1), kind="stable")
    at, size = starts[order], length[order]
    h = np.full(len(at), 0x51ED270B, np.uint64)
    heads = {}
    live = np.searchsorted(-size, -np.arange(1, LONG_WORD + 1), "right")
    for j in range(LONG_WORD):
        if not (n := int(live[j])):
            break
        h[:n] = h[:n] * _MULT + LOWER[data[at[:n] + j]] + np.uint64(1)
        if j + 1 in prefixes:
            heads[j + 1] = np.zeros(len(at), np.uint64)
            heads[j + 1][:n] = mix(h[:n] ^ np.uint64(j + 1))
    for i in range(int(np.searchsorted(-size, -LONG_WORD, "left"))):
        h[i] = np.uint64(xxhash.xxh3_64_intdigest(LOWER[data[at[i] : at[i] + size[i]]].tobytes()))
    out = np.empty_like(h)
    out[order] = mix(h + size.astype(np.uint64))
    back = {}
    for k in prefixes:
        v = heads.get(k, np.zeros(len(at), np.uint64))
        back[k] = np.empty_like(v)
        back[k][order] = v
    return out, back
