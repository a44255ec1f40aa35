"""Class-based bigram language model: word classes by the exchange algorithm, P(w | history) = P(class | previous class) P(w | class).

Tokens are runs without ASCII white space, A-Z in lower case, and one end token for each text. Words are named by 64-bit hashes.

Training, over all training texts: (1) counts of every word; (2) a start: the exchange algorithm on the bigrams of the `CORE`
commonest words, one symbol for all other words and the end; the others start in the class in which their last three (else two, else
one) bytes weigh most; (3) `WIDE_SWEEPS` exchange sweeps over the table of the `COMMON` commonest words: a pass over the texts counts for each of them
the classes before and after (a table bounded by words times classes), the core words move one by one on the driver, all others at once in tasks against
the class-by-class sums, and a sweep that does not raise the likelihood is taken back; (4) the words outside the table, in any number, are
exchanged from their own contexts in tasks, and their classes are joined to the bigrams that hold them; (5) transition counts of the final classes over
all training tokens, token and word totals of each class over all words. Words unseen in training take the class of their last bytes.
Transitions are smoothed towards the class distribution, emissions by adding 0.5 to
each word of the class and to one unseen word.

Scoring: a table of the `COMMON` commonest words, of fixed size, is broadcast. Tokens outside it become rows (text, word) that
are joined with the whole table of counts and classes, and their parts are summed per text; moves beside such tokens travel as class codes. A text
itself is never shuffled.

Null texts count as empty: one end token. Rows repeated whole are scored and counted each. With no training text the
model is uniform over one unseen word and the end. Columns of the input other than text pass through."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_bucket, materialize, prepare, table
from .words import slices, tokens

CORE, COMMON, CLASSES, SWEEPS, WIDE_SWEEPS, SMOOTHING = 2000, 1 << 18, 48, 6, 3, 20.0
PIECE, BATCH_MB = 1 << 18, 4  # bytes of text hashed at once; megabytes of an Arrow batch, which a task holds in the JVM and in Python
KEYS, BLOCK, FAN_IN = 128, 1 << 12, 512  # room for the classes after and before of a word; words of the table in a block; tasks merged at once
END = np.uint64(0x5EED5EED5EED5EED)


def token_stream(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tokens of the texts with each text's end token: hashes, last bytes, offsets by text. Hashing takes some sixty bytes for each byte
    of text, so it sees `PIECE` bytes of text at a time."""
    parts = [tokens(texts[i:j]) for i, j in slices(texts, PIECE)] or [tokens(texts)]
    h, tail = (np.concatenate([p[x] for p in parts]) for x in (0, 1))
    offsets = np.concatenate([[0], np.cumsum(np.concatenate([np.diff(p[2]) for p in parts]))])
    n = len(texts)
    ends = offsets[1:] + np.arange(n)
    word = np.ones(len(h) + n, bool)
    word[ends] = False
    all_h, all_tail = np.full(len(h) + n, END, np.uint64), np.zeros(len(h) + n, np.uint32)
    all_h[word], all_tail[word] = h, tail
    return all_h, all_tail, offsets + np.arange(n + 1)


class Lookup:
    """Word hash -> row of a small table. The first bits of a hash lead to the few keys that share them, as hashes are spread evenly; keys that are not
    cost time only."""

    def __init__(self, keys: np.ndarray):
        self.order = np.argsort(keys)
        self.keys = np.append(keys[self.order], np.uint64(0))  # one more, never a match: it lies behind every bucket
        bits = len(keys).bit_length() + 1
        self.shift = np.uint64(64 - bits)
        self.starts = np.append(0, np.cumsum(np.bincount((self.keys[:-1] >> self.shift).astype(np.int64), minlength=1 << bits))).astype(np.int32)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Row number, or -1."""
        bucket = (h >> self.shift).astype(np.int64)
        at, end = self.starts[bucket], self.starts[bucket + 1]
        out, left = np.full(len(h), -1), np.flatnonzero(at < end)
        at, end, h = at[left], end[left], h[left]
        while len(left):
            key = self.keys[at]
            hit = key == h
            out[left[hit]] = self.order[at[hit]]
            more = np.flatnonzero((key < h) & (at + 1 < end))
            left, at, end, h = left[more], at[more] + 1, end[more], h[more]
        return out


def xlogx(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log(np.maximum(x, 1)), 0.0)


def likelihood(pairs: np.ndarray) -> float:
    """Log likelihood of the bigrams under the class-by-class sums, up to a constant of the words."""
    return float(xlogx(pairs).sum() - xlogx(pairs.sum(axis=1)).sum() - xlogx(pairs.sum(axis=0)).sum())


def exchange(bigrams: np.ndarray, classes: int, fixed: int, sweeps: int = SWEEPS, start: tuple[np.ndarray, ...] | None = None) -> np.ndarray:
    """Classes of the symbols of a square matrix of bigram counts. The last `fixed` symbols keep a class each of their own,
    numbered from `classes`; the others start dealt out in order. Stops when a sweep moves nothing. `start`: classes to start from, counts of the
    class after and before by symbol, and class-by-class sums, which also hold neighbours outside the matrix; the sums are changed in place."""
    v, total = len(bigrams), classes + fixed
    free = v - fixed
    counts = bigrams.astype(np.float64)
    if start is None:
        of = np.concatenate([np.arange(free) % max(classes, 1), classes + np.arange(fixed)]).astype(np.int64)
        onehot = np.zeros((v, total))
        onehot[np.arange(v), of] = 1
        right, left = counts @ onehot, counts.T @ onehot  # by word: counts of the class after, before
        pairs = onehot.T @ right
    else:
        of, right, left, pairs = start[0].copy(), *start[1:]
    for _ in range(sweeps):
        moved = 0
        for w in range(free):
            a, r, l, own = of[w], right[w].copy(), left[w].copy(), counts[w, w]
            if r.sum() + l.sum() == 0:
                continue
            pairs[a] -= r
            pairs[:, a] -= l
            pairs[a, a] += own
            r[a] -= own
            l[a] -= own
            rows, cols = pairs.sum(axis=1) + l, pairs.sum(axis=0) + r  # wherever w goes, its neighbours' classes keep their counts
            b = np.arange(classes)
            gain = (xlogx(pairs + r) - xlogx(pairs)).sum(axis=1)[:classes] + (xlogx(pairs + l[:, None]) - xlogx(pairs)).sum(axis=0)[:classes]
            d, dr, dl = pairs[b, b], r[b], l[b]
            gain += xlogx(d + dr + dl + own) - xlogx(d + dr) - xlogx(d + dl) + xlogx(d)
            gain -= xlogx(rows[b] + r.sum() + own) - xlogx(rows[b]) + xlogx(cols[b] + l.sum() + own) - xlogx(cols[b])
            to = int(gain.argmax())
            if gain[to] <= gain[a] + 1e-9:
                to = a
            r[to] += own
            l[to] += own
            pairs[to] += r
            pairs[:, to] += l
            pairs[to, to] -= own
            if to != a:
                moved += 1
                of[w] = to
                right[:, a] -= counts[:, w]
                right[:, to] += counts[:, w]
                left[:, a] -= counts[w]
                left[:, to] += counts[w]
        if not moved:
            break
    return of


def reassign(pairs: np.ndarray, own: np.ndarray, word: np.ndarray, key: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The best class of each word against fixed class-by-class sums. own: class of each word now; (word, key, n): counts of its neighbouring
    classes, grouped by word; keys below the number of all classes are the class after, the others the class before."""
    c, lead = len(pairs), np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
    after = np.concatenate([pairs.T, pairs])[:, : c - 1]  # by key: the sums that a word of each class adds to
    gain = np.empty((len(own), c - 1))
    stay = np.empty(len(own))
    total = np.add.reduceat(np.where(key < c, n, 0), lead).astype(np.float64)
    step = 1 << 14
    cuts = [0]  # whole words, about `step` rows at a time
    while cuts[-1] < len(lead):
        cuts.append(max(cuts[-1] + 1, int(np.searchsorted(lead, lead[cuts[-1]] + step))))
    for i, j in zip(cuts[:-1], cuts[1:], strict=True):
        a, b = lead[i], lead[j] if j < len(lead) else len(word)
        some, at = np.unique(key[a:b] * (1 << 40) + n[a:b], return_inverse=True)  # few different (key, n): one table row each
        k, m = some >> 40, (some & ((1 << 40) - 1)).astype(np.float64)[:, None]
        more = xlogx(after[k] + m) - xlogx(after[k])
        less = xlogx(after[k]) - xlogx(np.maximum(after[k] - m, 0))
        gain[i:j] = np.add.reduceat(more[at], lead[i:j] - a, axis=0)
        stay[i:j] = np.add.reduceat(less[at, np.repeat(own[i:j], np.diff(np.append(lead[i:j], b)))], lead[i:j] - a)
    for sums in (pairs.sum(axis=1)[: c - 1], pairs.sum(axis=0)[: c - 1]):
        gain -= xlogx(sums + total[:, None]) - xlogx(sums)
        stay -= xlogx(sums[own]) - xlogx(np.maximum(sums[own] - total, 0))
    gain[np.arange(len(own)), own] = stay
    to = gain.argmax(axis=1)
    return np.where(gain[np.arange(len(own)), to] > stay + 1e-9, to, own)


class ClassModel:
    """The fitted parts of bounded size; `counts` is the table (h, n, c) of all words, their counts and classes."""

    def __init__(self, counts: DataFrame, total: int, distinct: int):
        self.counts, self.total, self.distinct = counts, total, distinct

    # -- rules that every task applies by itself
    def place(self, h: np.ndarray, tail: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row of each word in the table (-1: outside) and its class; outside the table that of its last bytes."""
        row = self.clustered.find(h)
        out = np.where(row >= 0, self.word_class[row], -1)
        left = np.flatnonzero(row < 0)
        for size in (3, 2, 1):
            keys, values = self.suffixes[size]
            if len(keys) and len(left):
                t = tail[left] & np.uint32((1 << 8 * size) - 1)
                at = np.minimum(np.searchsorted(keys, t), len(keys) - 1)
                same = keys[at] == t
                out[left[same]] = values[at[same]]
                left = left[~same]
        return row, np.where(h == END, CLASSES, np.where(out < 0, 0, out))

    def log_emission(self, n: np.ndarray, c: np.ndarray) -> np.ndarray:
        return np.log10((n + 0.5) / (self.class_tokens[c] + 0.5 * (self.class_words[c] + 1)))

    def log_base(self, n: np.ndarray) -> np.ndarray:
        return np.log10((n + 0.5) / (self.total + 0.5 * (self.distinct + 1)))

    @classmethod
    def fit(cls, docs: DataFrame, text: str = "text") -> ClassModel:
        spark = docs.sparkSession
        prepare(spark, BATCH_MB)
        texts = docs.select(F.col(text).alias("text"))

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for i, j in slices(b["text"]):
                    stream, tail, _ = token_stream(b["text"][i:j])
                    h, first, n = np.unique(stream, return_index=True, return_counts=True)
                    yield pa.record_batch({"h": h.view(np.int64), "tail": tail[first].astype(np.int32), "n": n.astype(np.int64)})

        counts = texts.mapInArrow(count, "h long, tail int, n long").groupBy("h").agg(F.first("tail").alias("tail"), F.sum("n").alias("n"))
        counts = materialize(counts, "word-counts")
        row = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
        model = cls(counts, int(row[0]), int(row[1]))
        words = counts.where(F.col("h") != int(END.view(np.int64)))
        # the least count with at most COMMON words at or above it, from a histogram of bounded size
        step, held, least = F.floor(F.log2("n") * 64).cast("int"), 0, None
        for r in words.groupBy(step.alias("step")).agg(F.count("*").alias("words"), F.min("n").alias("least")).orderBy(F.desc("step")).collect():
            held += r["words"]
            if held > COMMON:
                break
            least = r["least"]
        common = words.where(F.col("n") >= F.lit(least)).toArrow()
        order = np.lexsort((common["h"].to_numpy(), -common["n"].to_numpy()))
        hashes, tails, n = common["h"].to_numpy()[order].view(np.uint64), common["tail"].to_numpy()[order].astype(np.uint32), common["n"].to_numpy()[order].astype(np.int64)
        matrix = model._cluster(texts, hashes[:CORE], tails[:CORE], n[:CORE])
        seen = model._exchange_table(texts, matrix, hashes, tails)
        model._endings(tails, model.word_class[:-1], n)
        pairs, rare = model._exchange_outside(texts, seen)
        sent = spark.sparkContext.broadcast(RuleOnly(model))

        def classed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                row = sent.value.clustered.find(b["h"].to_numpy().view(np.uint64))
                yield pa.record_batch({"h": b["h"], "n": b["n"], "c": sent.value.word_class[row].astype(np.int8)})

        inside = (F.col("h") == int(END.view(np.int64))) | F.coalesce(F.col("n") >= F.lit(least), F.lit(False))
        known = counts.where(inside).select("h", "n").mapInArrow(classed, "h long, n long, c byte")
        model.counts = materialize(known.unionByName(counts.where(~inside).select("h", "n").join(rare, "h").select("h", "n", "c")), "lm-words")
        model._totals(pairs)
        model.common, model.common_n = model.clustered, np.append(n, int((counts.where(F.col("h") == int(END.view(np.int64))).agg(F.sum("n")).first()[0]) or 0))
        return model

    def _cluster(self, texts: DataFrame, hashes: np.ndarray, tails: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Classes to start from; returns the bigram counts of the core words and the end."""
        self.clustered = lookup = Lookup(hashes)
        size, k = len(hashes) + 2, len(hashes)
        sent = texts.sparkSession.sparkContext.broadcast(lookup)

        def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            matrix = np.zeros(size * size, np.int64)
            for b in batches:
                for i, j in slices(b["text"]):
                    h, _, offsets = token_stream(b["text"][i:j])
                    s = sent.value.find(h)
                    s = np.where(h == END, k + 1, np.where(s < 0, k, s))
                    before = np.concatenate([[k + 1], s[:-1]])
                    matrix += np.bincount(before * size + s, minlength=size * size)
            some = np.flatnonzero(matrix)
            for i in range(0, len(some), 100_000):
                yield pa.record_batch({"pair": some[i : i + 100_000], "n": matrix[some[i : i + 100_000]]})

        found = texts.mapInArrow(pairs, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).toArrow()
        matrix = np.zeros(size * size, np.int64)
        matrix[found["pair"].to_numpy()] = found["n"].to_numpy()
        matrix = matrix.reshape(size, size)
        self.word_class = exchange(matrix, CLASSES, 2)[:k] if k else np.zeros(0, np.int64)
        self._endings(tails, self.word_class, n)
        inner = np.append(np.arange(k), k + 1)
        return matrix[np.ix_(inner, inner)]

    def _endings(self, tails: np.ndarray, classes: np.ndarray, n: np.ndarray) -> None:
        self.suffixes = {}
        for bytes_ in (3, 2, 1):
            t = tails & np.uint32((1 << 8 * bytes_) - 1)
            keys, at = np.unique(t, return_inverse=True)
            weight = np.bincount(at * CLASSES + classes, weights=n, minlength=len(keys) * CLASSES).reshape(-1, CLASSES)
            self.suffixes[bytes_] = (keys, weight.argmax(axis=1) if len(keys) else np.zeros(0, np.int64))

    def _exchange_table(self, texts: DataFrame, matrix: np.ndarray, hashes: np.ndarray, tails: np.ndarray) -> np.ndarray:
        """Moves the words of the table (rows in order of frequency, the core first, then the end); returns the class-by-class sums
        over the bigrams of two words of the table."""
        spark, c, k, size = texts.sparkSession, CLASSES + 1, len(matrix) - 1, len(hashes)
        of = np.append(self.place(hashes, tails)[1], CLASSES)
        self.clustered, held = Lookup(np.append(hashes, END)), None
        for sweep in range(WIDE_SWEEPS + 1):
            self.word_class = of
            sums, contexts = context_counts(texts, RuleOnly(self))
            if held is not None and likelihood(sums[0]) <= likelihood(held[1][0]):
                of, sums = held
                break
            held = (of, sums)
            if sweep == WIDE_SWEEPS or not k:
                break
            first = contexts.where("block = 0").toArrow()
            dense = np.zeros(BLOCK * KEYS)
            for codes, n in zip(first["codes"], first["n"], strict=True):
                dense[np.frombuffer(codes.as_buffer(), np.int64)] = np.frombuffer(n.as_buffer(), np.int64)
            near = np.concatenate([dense.reshape(BLOCK, KEYS)[:k, : 2 * c], np.zeros((1, 2 * c))])
            moved = exchange(matrix, CLASSES, 1, 1, start=(np.append(of[:k], CLASSES), near[:, :c].copy(), near[:, c:].copy(), sums[0].astype(np.float64)))
            rest = best_in_table(contexts, of, sums[0], k).toArrow()
            of = of.copy()
            of[rest["row"].to_numpy()] = rest["c"].to_numpy()
            of[:k] = moved[:k]
        self.word_class = of
        return sums[1]

    def _exchange_outside(self, texts: DataFrame, seen: np.ndarray) -> tuple[np.ndarray, DataFrame]:
        """The class-by-class sums over all training tokens and the table (h, c) of the words outside the table. `seen`: the sums over
        bigrams within the table. The rows (a, b, oa, ob, ca, cb, n) are bigrams with a word outside; only such a word has its hash."""
        spark, c = texts.sparkSession, CLASSES + 1
        rule = spark.sparkContext.broadcast(RuleOnly(self))

        def bigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rest = np.zeros(c * c, np.int64)
            for b in batches:
                for i, j in slices(b["text"]):
                    h, tail, _ = token_stream(b["text"][i:j])
                    row, cls = rule.value.place(h, tail)
                    out, name = row < 0, np.where(row < 0, h, np.uint64(0))
                    a, oa, ca = (np.concatenate([np.array([x], y.dtype), y[:-1]]) for x, y in ((0, name), (False, out), (CLASSES, cls)))
                    some = np.flatnonzero(out | oa)
                    a, b_, oa, ob, ca, cb = (x[some] for x in (a, name, oa, out, ca, cls))
                    rest += np.bincount(ca * c + cb, minlength=c * c)
                    mixed = a * np.uint64(0x9E3779B97F4A7C15) + b_ * np.uint64(0xC2B2AE3D27D4EB4F) + (ca * c + cb).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
                    _, first, n = np.unique(mixed, return_index=True, return_counts=True)
                    for s in range(0, len(first), 100_000):
                        f = first[s : s + 100_000]
                        yield pa.record_batch({"a": a[f].view(np.int64), "b": b_[f].view(np.int64), "oa": oa[f], "ob": ob[f], "ca": ca[f].astype(np.int8), "cb": cb[f].astype(np.int8), "n": n[s : s + 100_000].astype(np.int64)})
            at, no = np.flatnonzero(rest), np.zeros(int((rest > 0).sum()), np.int64)
            yield pa.record_batch({"a": no, "b": no, "oa": no > 0, "ob": no > 0, "ca": (at // c).astype(np.int8), "cb": (at % c).astype(np.int8), "n": rest[at]})

        # counts stay those of a slice of texts: all that is made of them are sums
        labelled = materialize(texts.mapInArrow(bigrams, "a long, b long, oa boolean, ob boolean, ca byte, cb byte, n long"), "lm-bigrams")

        def by_class(rows: DataFrame) -> np.ndarray:
            out = np.zeros((c, c), np.int64)
            for r in rows.groupBy("ca", "cb").agg(F.sum("n").alias("n")).collect():
                out[r["ca"], r["cb"]] = r["n"]
            return out

        pairs = seen + by_class(labelled.where("not oa and not ob"))
        rare = materialize(best_outside(labelled.where("oa or ob"), pairs), "lm-classes")
        final = labelled.where("oa or ob")
        for flag, word, cls in (("oa", "a", "ca"), ("ob", "b", "cb")):
            joined = final.where(flag).drop(cls).join(rare.select(F.col("h").alias(word), F.col("c").alias(cls)), word)
            final = final.where(f"not {flag}").unionByName(joined)
        return seen + by_class(final), rare

    def _totals(self, matrix: np.ndarray) -> None:
        c = CLASSES + 1
        prior = (matrix.sum(axis=0) + 0.5) / (matrix.sum() + 0.5 * c)
        self.log_move = np.log10((matrix + SMOOTHING * prior) / (matrix.sum(axis=1, keepdims=True) + SMOOTHING))
        self.class_tokens, self.class_words = np.zeros(c), np.zeros(c)
        for r in self.counts.groupBy("c").agg(F.sum("n").alias("t"), F.count("*").alias("w")).collect():
            self.class_tokens[r["c"]], self.class_words[r["c"]] = r["t"], r["w"]

    def score(self, docs: DataFrame, text: str = "text") -> DataFrame:
        """docs without text, with n_tokens, n_known, base_score, score, perplexity."""
        prepare(docs.sparkSession, BATCH_MB)
        sent = docs.sparkSession.sparkContext.broadcast(RuleOnly(self))

        @F.arrow_udf("struct<n_tokens long, n_known long, base double, score double, word array<long>, class array<int>, times array<int>, moves array<int>>")
        def parts(texts: pa.Array) -> pa.Array:
            m, out = sent.value, []
            for i, j in slices(texts):
                h, tail, offsets = token_stream(texts[i:j].cast(pa.string()))
                row, c = m.place(h, tail)  # of words outside the table, the class if training has not seen them
                n = m.common_n[row]
                ends = np.zeros(len(h), bool)
                ends[offsets[:-1]] = True
                before = np.where(ends, CLASSES, np.concatenate([[CLASSES], c[:-1]]))
                known = row >= 0
                sure = known & (ends | np.concatenate([[True], known[:-1]]))
                move = np.where(sure, m.log_move[before, c], 0.0)
                base, emit = np.where(known, m.log_base(n), 0.0), np.where(known, m.log_emission(n, c), 0.0)
                doc = np.repeat(np.arange(j - i), np.diff(offsets))
                at = np.flatnonzero(~known)
                order = at[np.lexsort((h[at], doc[at]))]
                fresh = np.ones(len(order), bool)
                fresh[1:] = (h[order][1:] != h[order][:-1]) | (doc[order][1:] != doc[order][:-1])
                lead = np.flatnonzero(fresh)
                times = np.diff(np.concatenate([lead, [len(order)]]))
                first = order[lead]
                cut = pa.array(np.searchsorted(doc[first], np.arange(j - i + 1)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(cut, pa.array(x)) for x in (h[first].view(np.int64), c[first].astype(np.int32), times.astype(np.int32))]
                sums = [np.add.reduceat(x, offsets[:-1]) for x in (known.astype(np.int64), base, move + emit)]
                # moves into or out of words outside the table: class before and after, or -1 - (place in the text's list of words)
                code = c.astype(np.int32)
                code[order] = -1 - (np.cumsum(fresh) - 1 - cut.to_numpy()[doc[order]])
                open_ = np.flatnonzero(~sure)
                two = np.stack([np.where(ends, CLASSES, np.concatenate([[CLASSES], code[:-1]]))[open_], code[open_]], axis=1).ravel().astype(np.int32)
                lists.append(pa.ListArray.from_arrays(pa.array((2 * np.searchsorted(doc[open_], np.arange(j - i + 1))).astype(np.int32)), pa.array(two)))
                out.append(pa.StructArray.from_arrays([pa.array(np.diff(offsets)), *map(pa.array, sums), *lists], ["n_tokens", "n_known", "base", "score", "word", "class", "times", "moves"]))
            return pa.concat_arrays(out)

        rows = docs.withColumn("_p", parts(F.col(text))).drop(text).withColumn("_row", F.monotonically_increasing_id())
        rows = materialize(rows, "lm-parts")  # row numbers are fixed from here on
        rare = rows.select("_row", F.posexplode(F.arrays_zip("_p.word", "_p.class", "_p.times")).alias("at", "x")).select("_row", "at", F.col("x.word").alias("h"), F.col("x.class").alias("rule"), F.col("x.times").alias("times"))
        n, c = F.coalesce("n", F.lit(0)), F.coalesce(F.col("c").cast("int"), "rule")
        size = F.element_at(F.array(*[F.lit(float(t + 0.5 * (w + 1))) for t, w in zip(self.class_tokens, self.class_words, strict=True)]), c + 1)
        joined = rare.join(self.counts, "h", "left").select("_row", "at", c.alias("c"), (F.col("times") * F.when(n > 0, 1).otherwise(0)).alias("known"), (F.col("times") * F.log10((n + 0.5) / F.lit(self.total + 0.5 * (self.distinct + 1)))).alias("base"), (F.col("times") * F.log10((n + 0.5) / size)).alias("emit"))
        extra = joined.groupBy("_row").agg(F.sum("known").alias("_known"), F.sum("base").alias("_base"), F.sum("emit").alias("_emit"), F.transform(F.sort_array(F.collect_list(F.struct("at", "c"))), lambda x: x["c"]).alias("_classes"))

        @F.arrow_udf("double")
        def moved(moves: pa.Array, classes: pa.Array) -> pa.Array:
            out = np.zeros(len(moves))
            for i in range(len(moves)):
                x, c = moves[i].values, classes[i].values
                if x is not None and len(x):
                    x = x.to_numpy()
                    if c is not None and len(c):
                        x = np.where(x < 0, c.to_numpy(zero_copy_only=False)[np.maximum(-1 - x, 0)], x)
                    out[i] = sent.value.log_move[x[::2], x[1::2]].sum()
            return pa.array(out)

        zero = lambda x: F.coalesce(x, F.lit(0))
        own = [c for c in docs.columns if c != text]
        out = rows.select(*[f"`{c}`" for c in own], "_row", F.struct("_p.n_tokens", "_p.n_known", "_p.base", "_p.score", "_p.moves").alias("_p")).join(extra, "_row", "left")
        out = out.withColumns({"n_tokens": F.col("_p.n_tokens"), "n_known": (F.col("_p.n_known") + zero("_known")).cast("long"), "base_score": F.col("_p.base") + zero("_base"), "score": F.col("_p.score") + zero("_emit") + moved("_p.moves", "_classes")})
        return out.withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens"))).drop("_row", "_p", "_known", "_base", "_emit", "_classes")


def combined(codes: list[np.ndarray], n: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Different codes in order, with the sums of their counts."""
    every, back = np.unique(np.concatenate(codes), return_inverse=True)
    return every, np.bincount(back, weights=np.concatenate(n), minlength=len(every)).astype(np.int64)


def context_counts(texts: DataFrame, rule: ClassModel) -> tuple[tuple[np.ndarray, np.ndarray], DataFrame]:
    """Class-by-class sums over all bigrams and over those of two words of the table, and a table (block, codes, n): for each word of the table how often
    each class comes after and before it, as row * KEYS + class and row * KEYS + classes + class. Tasks merge their own counts, then `FAN_IN` tasks
    at a time, then all of a block, whose size is bounded."""
    sent, c = texts.sparkSession.sparkContext.broadcast(rule), CLASSES + 1

    def packed(block: int, salt: int, codes: np.ndarray, n: np.ndarray) -> dict:
        steps = np.diff(codes, prepend=0).astype(np.int64)
        raw = np.stack([steps, n]).view(np.uint8).reshape(2, -1, 8).transpose(0, 2, 1).tobytes()  # like bytes beside each other
        return {"block": block, "salt": salt, "size": len(n), "packed": pa.compress(raw, codec="zstd", asbytes=True)}

    schema = pa.schema([("block", pa.int32()), ("salt", pa.int32()), ("size", pa.int64()), ("packed", pa.binary())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, held, salt = np.zeros((2, c * c), np.int64), [[], []], TaskContext.get().partitionId() // FAN_IN
        for b in batches:
            for i, j in slices(b["text"]):
                h, tail, _ = token_stream(b["text"][i:j])
                row, cls = sent.value.place(h, tail)
                row_before = np.concatenate([[len(sent.value.word_class) - 1], row[:-1]])
                before = np.concatenate([[CLASSES], cls[:-1]])
                sums[0] += np.bincount(before * c + cls, minlength=c * c)
                both = (row >= 0) & (row_before >= 0)
                sums[1] += np.bincount(before[both] * c + cls[both], minlength=c * c)
                some = row_before >= 0
                code = np.concatenate([row_before[some] * KEYS + cls[some], row[row >= 0] * KEYS + c + before[row >= 0]])
                for x, y in zip(held, np.unique(code, return_counts=True), strict=True):
                    x.append(y)
                if sum(map(len, held[0])) > 1 << 20:
                    held = [[x] for x in combined(*held)]
        out = [packed(-1, salt, np.flatnonzero(sums.ravel()), sums.ravel()[np.flatnonzero(sums.ravel())])]
        if held[0]:
            codes, n = combined(*held)
            cuts = np.flatnonzero(np.diff(codes // (BLOCK * KEYS), prepend=-1))
            for a, b in zip(cuts, np.append(cuts[1:], len(codes)), strict=True):
                block = int(codes[a]) // (BLOCK * KEYS)
                out.append(packed(block, salt, codes[a:b] - block * BLOCK * KEYS, n[a:b]))
        yield pa.RecordBatch.from_pylist(out, schema)

    def summed(batches: Iterator[pa.RecordBatch], row: Callable) -> Iterator[pa.RecordBatch]:
        """Rows sorted by block and salt; one row for each."""
        name, dense = None, np.zeros(BLOCK * KEYS, np.int64)

        def whole() -> pa.RecordBatch:
            codes = np.flatnonzero(dense)
            return row(*name, codes, dense[codes])

        for b in batches:
            for r in b.to_pylist():
                if name != (r["block"], r["salt"]):
                    if name is not None:
                        yield whole()
                    name, dense[:] = (r["block"], r["salt"]), 0
                codes, n = unpacked(r["size"], r["packed"])
                dense[codes] += n
        if name is not None:
            yield whole()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return summed(batches, lambda *row: pa.RecordBatch.from_pylist([packed(*row)], schema))

    def opened(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:  # sums as well: two Python stages in a row would run two processes for each task
        return summed(batches, lambda block, _, codes, n: pa.record_batch({"block": pa.array([block], pa.int32()), "codes": [codes.tobytes()], "n": [n.tobytes()]}))

    kind = "block int, salt int, size long, packed binary"
    rows = texts.mapInArrow(count, kind).repartition("block", "salt").sortWithinPartitions("block", "salt").mapInArrow(merge, kind)
    rows = rows.withColumn("salt", F.lit(0)).repartition("block").sortWithinPartitions("block", "salt")
    contexts = materialize(rows.mapInArrow(opened, "block int, codes binary, n binary"), "lm-contexts")
    sent.destroy()
    sums = np.zeros(2 * c * c, np.int64)
    got = contexts.where("block = -1").toArrow()
    for codes, n in zip(got["codes"], got["n"], strict=True):
        sums[np.frombuffer(codes.as_buffer(), np.int64)] = np.frombuffer(n.as_buffer(), np.int64)
    return tuple(sums.reshape(2, c, c)), contexts.where("block >= 0")


def unpacked(size: int, data: bytes) -> tuple[np.ndarray, np.ndarray]:
    raw = np.frombuffer(pa.decompress(data, decompressed_size=16 * size, codec="zstd", asbytes=True), np.uint8)
    steps, n = np.ascontiguousarray(raw.reshape(2, 8, size).transpose(0, 2, 1)).view(np.int64).reshape(2, size)
    return np.cumsum(steps), n


def best_in_table(contexts: DataFrame, of: np.ndarray, pairs: np.ndarray, core: int) -> DataFrame:
    """(row, c) of every word of the table below the core, each by its contexts against the same sums."""
    sent = contexts.sparkSession.sparkContext.broadcast((of, pairs))

    def choose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of, pairs = sent.value
        for b in batches:
            for r in b.to_pylist():
                code = np.frombuffer(r["codes"], np.int64) + r["block"] * BLOCK * KEYS
                row, n = code // KEYS, np.frombuffer(r["n"], np.int64)
                some = (row >= core) & (row < len(of) - 1)
                words, word = np.unique(row[some], return_inverse=True)
                if len(words):
                    yield pa.record_batch({"row": words, "c": reassign(pairs, of[words], word, code[some] % KEYS, n[some]).astype(np.int8)})

    return contexts.mapInArrow(choose, "row long, c byte")


def best_outside(labelled: DataFrame, pairs: np.ndarray) -> DataFrame:
    """(h, c) of every word outside the table, from its counts of neighbouring classes."""
    c = CLASSES + 1
    sent = labelled.sparkSession.sparkContext.broadcast(pairs)

    def contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            a, b, oa, ob, ca, cb, n = (rows[x].to_numpy(zero_copy_only=False) for x in ("a", "b", "oa", "ob", "ca", "cb", "n"))
            yield pa.record_batch({"h": np.concatenate([a[oa], b[ob]]), "own": np.concatenate([ca[oa], cb[ob]]), "key": np.concatenate([cb[oa], c + ca[ob]]).astype(np.int8), "n": np.concatenate([n[oa], n[ob]])})

    def chosen(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        h, own, key, n = (np.concatenate([p[x].to_numpy() for p in parts]) for x in ("h", "own", "key", "n"))
        words, first, word = np.unique(h, return_index=True, return_inverse=True)
        at, back = np.unique(word * (2 * c) + key, return_inverse=True)
        total = np.bincount(back, weights=n).astype(np.int64)
        return pa.record_batch({"h": words, "c": reassign(sent.value, own[first].astype(np.int64), at // (2 * c), at % (2 * c), total).astype(np.int8)})

    def choose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for b in batches:
            if not b.num_rows:
                continue
            last = b["h"].to_numpy()
            if rows >= 200_000 and last[-1] != held[-1]["h"][-1].as_py():
                cut = int((last == held[-1]["h"][-1].as_py()).sum())  # sorted: the rest of the word stands first
                yield chosen([*held, b.slice(0, cut)])
                held, rows, b = [], 0, b.slice(cut)
            held.append(b)
            rows += b.num_rows
        if held:
            yield chosen(held)

    found = labelled.mapInArrow(contexts, "h long, own byte, key byte, n long")
    return found.repartition("h").sortWithinPartitions("h").mapInArrow(choose, "h long, c byte")


class RuleOnly(ClassModel):
    """The model without its tables, for sending to tasks."""

    def __init__(self, model: ClassModel):
        for name in ("total", "distinct", "clustered", "word_class", "suffixes", "class_tokens", "class_words", "log_move", "common", "common_n"):
            if hasattr(model, name):
                setattr(self, name, getattr(model, name))


def op4_class_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("held_out", crc_bucket("doc_id", 5) == 1)
    model = ClassModel.fit(docs.where(~F.col("held_out")))
    return model.score(docs).withColumn("train_tokens", F.lit(model.total).cast("long")).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score")
