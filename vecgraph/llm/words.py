"""Word hashes and shingles of whole Arrow batches in numpy.

A word is a maximal run of ASCII letters, digits or characters beyond ASCII, in lower case. A shingle is five words in
a row; a text of one to four words has one shingle of all its words; a text without a word has none. All numbers are
64-bit hashes: two given words collide with probability about 2^-64."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK = 1 << 21
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_TOKEN = np.ones(256, bool)
_TOKEN[[32, *range(9, 14)]] = False
_ASCII_LOWER = np.arange(256, dtype=np.uint8)
_ASCII_LOWER[65:91] += 32
_POWERS: dict[str, np.ndarray] = {}
MULTIPLIERS = np.array([pow(0xD1342543DE82EF95, i + 1, 1 << 64) for i in range(8)], np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit numbers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS.get("up", ())) < n:
        m = max(n, 2 * len(_POWERS.get("up", ())))  # sixteen bytes for each byte of the longest text so far
        for key, base in (("up", _BASE), ("down", _INVERSE)):
            p = np.full(m, base, np.uint64)
            p[0] = 1
            np.multiply.accumulate(p, out=p)
            _POWERS[key] = p
    return _POWERS["up"][:n], _POWERS["down"][:n]


def slices(texts: pa.Array, limit: int = CHUNK) -> Iterator[tuple[int, int]]:
    """Row ranges of at most `limit` bytes of text (one row at least)."""
    ends = np.concatenate([[0], np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False))])
    i = 0
    while i < len(texts):
        j = max(i + 1, int(np.searchsorted(ends, ends[i] + limit, "right")) - 1)
        yield i, min(j, len(texts))
        i = j


def _bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts (null: empty) and the offsets of each."""
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    if not len(texts):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    first, last = int(offsets[0]), int(offsets[-1])
    data = np.frombuffer(texts.buffers()[2], np.uint8)[first:last] if last > first else np.zeros(0, np.uint8)
    return data, offsets - first


def runs(data: np.ndarray, offsets: np.ndarray, inside_table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes of the table; a run never crosses the end of a text."""
    inside = inside_table[data]
    fresh = np.ones(len(data) + 1, bool)
    fresh[1:-1] = ~inside[:-1]
    fresh[offsets] = True
    closing = np.ones(len(data), bool)
    closing[:-1] = ~inside[1:]
    closing[offsets[offsets > 0] - 1] = True
    return np.flatnonzero(inside & fresh[:-1]), np.flatnonzero(inside & closing) + 1


def run_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each run of bytes."""
    up, down = _powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:-1], out=total[1:])
    return mix((total[ends] - total[starts]) * down[starts])


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of the texts in order, and the offsets of each text's words."""
    data, offsets = _bytes(pc.utf8_lower(texts))
    starts, ends = runs(data, offsets, _WORD)
    return run_hashes(data, starts, ends), np.searchsorted(starts, offsets)


def tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tokens between ASCII white space, A-Z in lower case: hashes, the last three bytes of each as one number, offsets by text."""
    data, offsets = _bytes(texts)
    data = _ASCII_LOWER[data]
    starts, ends = runs(data, offsets, _TOKEN)
    size = ends - starts
    padded = np.concatenate([np.zeros(3, np.uint32), data.astype(np.uint32)])
    tail = padded[ends + 2]
    tail = np.where(size > 1, tail | padded[ends + 1] << 8, tail)
    tail = np.where(size > 2, tail | padded[ends] << 16, tail)
    return run_hashes(data, starts, ends), tail, np.searchsorted(starts, offsets)


def shingles(words: np.ndarray, offsets: np.ndarray, size: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all shingles in order, the offsets of each text's shingles, and the word at which each begins."""
    n, count = len(words), np.diff(offsets)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64), np.zeros(0, np.int64)
    padded = np.concatenate([words, np.zeros(size - 1, np.uint64)])
    acc = np.zeros(n, np.uint64)
    for j in range(size):
        acc += padded[j : n + j] * MULTIPLIERS[j]
    keep = np.arange(n) <= np.repeat(offsets[1:] - size, count)
    short = np.flatnonzero((count > 0) & (count < size))
    if len(short):
        at = offsets[:-1][short]
        value = count[short].astype(np.uint64)
        for j in range(size - 1):
            value = value + np.where(count[short] > j, padded[at + j], np.uint64(0)) * MULTIPLIERS[j]
        acc[at], keep[at] = value, True
    kept = np.where(count >= size, count - size + 1, (count > 0).astype(np.int64))
    return mix(acc[keep]), np.concatenate([[0], np.cumsum(kept)]), np.flatnonzero(keep)


def sequence_keys(words: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Per text a 64-bit hash of its words in order."""
    count = np.diff(offsets)
    place = np.arange(len(words)) - np.repeat(offsets[:-1], count)
    up = _powers(max(int(count.max(initial=0)), 1))[0]
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(words * up[place], dtype=np.uint64)])
    return mix(total[offsets[1:]] - total[offsets[:-1]] + mix(count.astype(np.uint64)))


def permutations(n: int, seed: int = 7) -> np.ndarray:
    return np.random.default_rng(seed).integers(1 << 32, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def minhash(values: np.ndarray, starts: np.ndarray, multipliers: np.ndarray) -> np.ndarray:
    """(len(starts), len(multipliers)) least permuted values of consecutive non-empty runs that begin at starts."""
    out = np.empty((len(starts), len(multipliers)), np.uint64)
    if len(starts):
        for i, m in enumerate(multipliers):
            out[:, i] = np.minimum.reduceat(values * m, starts)
    return out
