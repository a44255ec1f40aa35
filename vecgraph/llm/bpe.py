"""Token ids of a public tokenizer, word by word, with a cache and a numpy merger for new words.

White space never takes part in a token of the word-BPE tokenizer, so a text's ids are those of its words in order. New words that are letters with punctuation
behind them are merged many at a time: all words advance by their pair of lowest rank in lock-step. Every other new word, and every word
of a tokenizer of another make, goes to the tokenizers library itself; both ways give the same ids."""

from __future__ import annotations

import json
import os

import numpy as np
import pyarrow as pa

from .words import _ASCII_LOWER, _bytes, run_hashes, runs, word_hashes

_NONE = np.int32(1 << 30)
LONGEST = 48


def _byte_chars() -> list[str]:
    """The character that stands for each byte in byte-level vocabularies: printable Latin-1 characters for themselves, the others from 256 up."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    out, extra = [], 256
    for b in range(256):
        out.append(chr(b) if b in own else chr(extra))
        extra += b not in own
    return out


class Merger:
    """Merges of a byte-level vocabulary with a suffix at word ends."""

    def __init__(self, vocab: dict[str, int], merges: list, suffix: str):
        chars = _byte_chars()
        self.first = np.array([vocab.get(c, -1) for c in chars], np.int32)
        self.last = np.array([vocab.get(c + suffix, -1) for c in chars], np.int32)
        pairs = [m if isinstance(m, list | tuple) else m.split(" ") for m in merges]
        left, right, into = (np.array([vocab[f(p)] for p in pairs], np.uint64) for f in (lambda p: p[0], lambda p: p[1], lambda p: p[0] + p[1]))
        self.bits = 18
        self.keys = np.full(1 << self.bits, np.uint64(1 << 63), np.uint64)
        self.rank, self.into = np.full(1 << self.bits, _NONE, np.int32), np.zeros(1 << self.bits, np.int32)
        key, todo, at = left << np.uint64(20) | right, np.arange(len(pairs)), None
        at = self._slot(key)
        self.probes = 0
        while len(todo):  # linear probing: of those that want a free slot the first takes it
            self.probes += 1
            free = self.keys[at[todo]] == np.uint64(1 << 63)
            want, pick = np.unique(at[todo][free], return_index=True)
            won = todo[np.flatnonzero(free)[pick]]
            self.keys[want], self.rank[want], self.into[want] = key[won], won, into[won]
            todo = np.setdiff1d(todo, won)
            at[todo] = (at[todo] + 1) & ((1 << self.bits) - 1)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Slots of pairs in the table, -1 where two tokens do not merge."""
        key = (a.astype(np.uint64) << np.uint64(20) | b.astype(np.uint64)).ravel()
        at = self._slot(key)
        out = np.where(self.keys[at] == key, at, -1)
        open_ = np.flatnonzero((out < 0) & (self.keys[at] != np.uint64(1 << 63)))
        for _ in range(self.probes):
            if not len(open_):
                break
            at[open_] = (at[open_] + 1) & ((1 << self.bits) - 1)
            got = self.keys[at[open_]]
            hit = got == key[open_]
            out[open_[hit]] = at[open_[hit]]
            open_ = open_[~hit & (got != np.uint64(1 << 63))]
        return out.reshape(a.shape)

    def encode(self, data: np.ndarray, starts: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of lower-case words given by their place in data, of at most LONGEST bytes: the ids of all words in order, and how many each has."""
        count, parts = np.zeros(len(size), np.int64), []
        edges = [0, 6, 8, 10, 12, 14, 16, 20, 24, 32, LONGEST]
        padded = np.concatenate([data, np.zeros(LONGEST, np.uint8)])
        for lo, hi in zip(edges[:-1], edges[1:], strict=True):
            group = np.flatnonzero((size > lo) & (size <= hi))
            for s in range(0, len(group), 20_000):
                part = group[s : s + 20_000]
                sym, n = self._merge(padded[starts[part][:, None] + np.arange(hi)], size[part], hi)
                count[part] = n
                parts.append((part, n, sym))
        at = np.concatenate([[0], np.cumsum(count)])
        out = np.zeros(int(at[-1]), np.uint32)
        for part, n, sym in parts:
            own = np.arange(sym.shape[1]) < n[:, None]
            out[(at[part][:, None] + np.arange(sym.shape[1]))[own]] = sym[own]
        return out, count

    def _merge(self, raw: np.ndarray, size: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        rows, cols = np.arange(len(raw)), np.arange(width)
        sym = self.first[raw]
        sym[rows, size - 1] = self.last[raw[rows, size - 1]]
        slot = self.find(sym[:, :-1], sym[:, 1:])
        rank = np.where((slot >= 0) & (cols[1:] < size[:, None]), self.rank[slot], _NONE)
        n, live = size.copy(), rows
        final = sym.copy()
        while True:
            best = rank.argmin(axis=1)
            go = rank[np.arange(len(live)), best] < _NONE
            if not go.all():
                final[live[~go]] = sym[~go]
                live, sym, rank, best = live[go], sym[go], rank[go], best[go]
            if not len(live):
                return final, n
            at = np.arange(len(live))
            slot = self.find(sym[at, best], sym[at, best + 1])
            moved = np.minimum(cols + (cols > best[:, None]), width - 1)
            sym = np.take_along_axis(sym, moved, 1)
            sym[at, best] = self.into[slot]
            rank = np.take_along_axis(rank, np.minimum(cols[:-1] + (cols[:-1] > best[:, None]), width - 2), 1)
            n[live] -= 1
            rank[np.arange(len(live))[:, None], np.maximum(n[live] - 1, 0)[:, None]] = _NONE
            for step in (-1, 0):
                p = best + step
                ok = (p >= 0) & (p + 1 < n[live])
                s = self.find(sym[at[ok], p[ok]], sym[at[ok], p[ok] + 1])
                rank[at[ok], p[ok]] = np.where(s >= 0, self.rank[s], _NONE)


_LETTER, _PUNCT, _SPACE = np.zeros(256, bool), np.zeros(256, bool), np.zeros(256, bool)
_LETTER[97:123] = True
_PUNCT[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True
_SPACE[[32, *range(9, 14)]] = True


def lower(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes with ASCII and Latin-1 letters in lower case, and which bytes belong to such letters."""
    low = _ASCII_LOWER[data]
    second = np.flatnonzero(data[:-1] == 0xC3) + 1
    v = low[second]
    up = (v >= 0x80) & (v <= 0x9E) & (v != 0x97)
    low[second[up]] += 0x20
    letter = _LETTER[low]
    good = second[(v != 0x97) & (v != 0xB7)]
    letter[good] = letter[good - 1] = True
    return low, letter


class WordEncoder:
    """Ids of texts by a tokenizer file. The cache is three arrays by word hash and holds at most `held` words, about 30 bytes each."""

    def __init__(self, path: str, held: int = 1_000_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.held = Tokenizer.from_file(path), held
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        normal, pre = json.dumps(spec.get("normalizer")), json.dumps(spec.get("pre_tokenizer"))
        known = '"Lowercase"' in normal and "[\\\\p{L}]+" in pre and model.get("type") == "BPE" and model.get("end_of_word_suffix") == "</w>" and not model.get("ignore_merges")
        self.merger = Merger(model["vocab"], model["merges"], "</w>") if known else None
        self._reset()

    def _reset(self) -> None:
        self.h, self.at, self.n = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int32)
        self.flat, self.used = np.zeros(1 << 20, np.uint32), 0
        self.tails: dict[bytes, np.ndarray] = {}

    def _library(self, words: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch(words, add_special_tokens=False)] if words else []

    def _keep(self, h: np.ndarray, ids: np.ndarray, count: np.ndarray) -> None:
        while self.used + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros(len(self.flat), np.uint32)])
        self.flat[self.used : self.used + len(ids)] = ids
        starts = self.used + np.cumsum(count) - count
        self.used += len(ids)
        order = np.argsort(h)
        where = np.searchsorted(self.h, h[order])
        self.h, self.at, self.n = np.insert(self.h, where, h[order]), np.insert(self.at, where, starts[order]), np.insert(self.n, where, count[order])

    def _learn(self, h: np.ndarray, data: np.ndarray, low: np.ndarray, starts: np.ndarray, core: np.ndarray, ends: np.ndarray, plain: np.ndarray) -> None:
        if len(self.h) + len(h) > self.held:
            self._reset()
        p = np.flatnonzero(plain)
        if len(p):
            ids, count = self.merger.encode(low, starts[p], core[p] - starts[p])
            tail = [low[a:b].tobytes() for a, b in zip(core[p].tolist(), ends[p].tolist(), strict=True)]
            new = [t for t in {*tail} - self.tails.keys() if t]
            self.tails.update(zip(new, self._library([t.decode() for t in new]), strict=True))
            extra = np.array([len(self.tails[t]) if t else 0 for t in tail], np.int64)
            if extra.any():
                total = count + extra
                place = np.cumsum(total) - total
                out = np.zeros(int(total.sum()), np.uint32)
                out[np.repeat(place - (np.cumsum(count) - count), count) + np.arange(len(ids))] = ids
                by: dict[bytes, list[int]] = {}
                for i in np.flatnonzero(extra).tolist():
                    by.setdefault(tail[i], []).append(i)
                for t, members in by.items():
                    at = np.array(members)
                    for k, x in enumerate(self.tails[t].tolist()):
                        out[place[at] + count[at] + k] = x
                ids, count = out, total
            self._keep(h[p], ids, count)
        r = np.flatnonzero(~plain)
        if len(r):
            got = self._library([data[a:b].tobytes().decode() for a, b in zip(starts[r].tolist(), ends[r].tolist(), strict=True)])
            self._keep(h[r], np.concatenate(got), np.array([len(x) for x in got], np.int64))

    def encode(self, texts: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Of a slice of texts: all ids with an end id behind each text, offsets of the texts' ids, a hash for each word (without punctuation behind it), offsets of the texts' words."""
        data, offsets = _bytes(texts)
        if self.merger is None or b"<|" in data.tobytes():  # another make, or strings that may be special tokens: the library alone
            rows = [np.append(x, np.uint32(end_id)) for x in self._library([t or "" for t in texts.to_pylist()])]
            words, word_offsets = word_hashes(texts)
            return np.concatenate([np.zeros(0, np.uint32), *rows]), np.concatenate([[0], np.cumsum([len(x) for x in rows])]).astype(np.int64), words, word_offsets
        low, letter = lower(data)
        starts, ends = runs(data, offsets, ~_SPACE)
        punct = _PUNCT[low]
        sums = lambda x: np.concatenate([[0], np.cumsum(x, dtype=np.int32)])
        strange, letters = sums(~(letter | punct)), sums(letter)
        back = sums(punct[:-1] & letter[1:])
        size = letters[ends] - letters[starts]
        plain = (strange[ends] == strange[starts]) & (back[np.maximum(ends - 1, 0)] == back[starts]) & (size <= LONGEST)
        if len(starts):
            plain &= letter[starts]
        core = np.where(plain, starts + size, ends)
        hashes = run_hashes(low, np.concatenate([starts, starts]), np.concatenate([ends, core]))
        h, term = hashes[: len(starts)], hashes[len(starts) :]
        u, first, back_to = np.unique(h, return_index=True, return_inverse=True)
        lacking = self._lacking(u)
        if lacking.any():
            i = first[lacking]
            if len(self.h) + len(i) > self.held:
                self._reset()
                i = first
            self._learn(h[i], data, low, starts[i], core[i], ends[i], plain[i])
        where = np.searchsorted(self.h, u)
        at, n = self.at[where][back_to], self.n[where][back_to].astype(np.int64)
        place = np.cumsum(n) - n
        ids = self.flat[np.repeat(at - place, n) + np.arange(int(n.sum()))]
        words = np.searchsorted(starts, offsets)
        cuts = np.concatenate([place, [len(ids)]])[words]
        return np.insert(ids, cuts[1:], np.uint32(end_id)), cuts + np.arange(len(cuts)), term, words

    def _lacking(self, u: np.ndarray) -> np.ndarray:
        if not len(self.h):
            return np.ones(len(u), bool)
        return self.h[np.minimum(np.searchsorted(self.h, u), len(self.h) - 1)] != u
