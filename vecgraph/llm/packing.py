"""Sequence packing guided by lexical retrieval: a sharded BM25 index returns unused neighbours for each seed document, which
greedily fill its window.

Tokenizing gives each document its number of ids and, for every 64 ids, a CRC-32, from which the checksum of any piece cut at
multiples of 64 follows by the algebra of CRCs; so ids are made once and never stored or shuffled. Documents are ordered by a hash of the least hash
of their words, which brings near copies and documents that share rare words together, and dealt into shards of a bounded number of documents.
Each shard has its own inverted index over words named by 32-bit hashes, whose document frequencies over all documents are kept for 262,144 groups of words; the seed is the longest unused document,
neighbours come in the order of their BM25 score, whole where they fit, and the best one that does not fit is cut to fill the window. Full windows of
long documents are sequences of their own. The last, unfilled window of a shard is split into sequences whose lengths are powers of two, which need no padding;
fewer than 64 ids remain for a padded one.

Every id of every document, with its end id, is in exactly one piece. Null texts count as empty and have only the end id; rows repeated whole are packed
each for itself. An empty table gives an empty result. Sequence ids are unique, not consecutive."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import WordEncoder
from .common import materialize, prepare, table
from .words import mix, slices

WINDOW, UNIT, SHARD, GROUPS, MORE, FAN_IN = 4096, 64, 2048, 18, 65535, 16
K1, LENGTH_WEIGHT = 1.2, 0.75
_ENCODERS: dict[str, WordEncoder] = {}


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encoder(path: str) -> WordEncoder:
    """The encoder and its cache live as long as the worker."""
    if path not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


def _operators() -> np.ndarray:
    """For n = 0..64 ids: tables (4, 256) of the linear map that appending n ids of zero bytes has on a CRC-32, without the final inversions."""
    step = np.zeros(32, np.uint64)  # images of single bits under one zero bit
    step[0] = 0xEDB88320
    step[1:] = 1 << np.arange(31, dtype=np.uint64)

    def apply(m: np.ndarray, v: np.ndarray) -> np.ndarray:
        r = np.zeros_like(v)
        for bit in range(32):
            r ^= np.where(v >> np.uint64(bit) & np.uint64(1), m[bit], np.uint64(0))
        return r

    for _ in range(5):  # 32 zero bits: one id
        step = apply(step, step)
    power, out = np.uint64(1) << np.arange(32, dtype=np.uint64), []
    for _ in range(UNIT + 1):
        out.append(np.stack([apply(power, np.arange(256, dtype=np.uint64) << np.uint64(8 * k)) for k in range(4)]))
        power = apply(step, power)
    return np.stack(out)


def joined_crc(parts: np.ndarray, last: int, tables: np.ndarray) -> int:
    """CRC-32 of consecutive units from theirs; all but the last have 64 ids, the last has `last`."""
    crc = 0
    for i, p in enumerate(parts.tolist()):
        t = tables[UNIT if i < len(parts) - 1 else last]
        crc = int(t[0, crc & 255] ^ t[1, crc >> 8 & 255] ^ t[2, crc >> 16 & 255] ^ t[3, crc >> 24]) ^ p
    return crc


def measured(docs: DataFrame, key: str, text: str, tokenizer: str, end_id: int) -> DataFrame:
    """A table of (id, row, n, crcs, terms, times, route): what packing needs of each document."""
    prepare(docs.sparkSession, 4)

    @F.arrow_udf("struct<n long, crcs binary, terms binary, times binary, route long>")
    def measure(texts: pa.Array) -> pa.Array:
        n, crcs, terms, times, route = [], [], [], [], []
        for i, j in slices(texts, 1 << 20):
            ids, cut_ids, h, offsets = encoder(tokenizer).encode(texts[i:j].cast(pa.string()), end_id)
            raw, bounds = memoryview(ids.astype("<u4").tobytes()), (4 * cut_ids).tolist()
            n += np.diff(cut_ids).tolist()
            crcs += [np.array([zlib.crc32(raw[a : min(a + 4 * UNIT, e)]) for a in range(s, e, 4 * UNIT)], np.uint32).tobytes() for s, e in zip(bounds[:-1], bounds[1:], strict=True)]
            doc = np.repeat(np.arange(j - i), np.diff(offsets))
            pairs, count = np.unique(doc.astype(np.uint64) << np.uint64(32) | h >> np.uint64(32), return_counts=True)
            if (count > MORE).any():  # a count of 0 is MORE further times of the term before
                extra = (count - 1) // MORE
                head = np.arange(len(count)) + np.cumsum(extra) - extra
                pairs, rest = np.repeat(pairs, extra + 1), count - extra * MORE
                count = np.zeros(len(pairs), np.int64)
                count[head] = rest
            cut = np.searchsorted(pairs, np.arange(j - i + 1, dtype=np.uint64) << np.uint64(32))
            term, tf = pairs.astype(np.uint32), count.astype(np.uint16)
            least = np.zeros(j - i, np.uint64)
            some = np.flatnonzero(np.diff(offsets))
            if len(some):
                least[some] = np.minimum.reduceat(mix(h), offsets[:-1][some])
            route += mix(least).view(np.int64).tolist()  # mixed again: the least hash falls with a text's length, and long texts shall be spread
            for a, b in zip(cut[:-1], cut[1:], strict=True):
                terms.append(term[a:b].tobytes())
                times.append(tf[a:b].tobytes())
        return pa.StructArray.from_arrays([pa.array(n, pa.int64()), *(pa.array(x, pa.binary()) for x in (crcs, terms, times)), pa.array(route, pa.int64())], ["n", "crcs", "terms", "times", "route"])

    rows = docs.select(F.col(key).alias("id"), measure(F.col(text).cast("string")).alias("m"))
    return materialize(rows.select("id", F.monotonically_increasing_id().alias("row"), "m.*"), "packing-rows")


def _statistics(rows: DataFrame) -> tuple[np.ndarray, float]:
    """Inverse document frequency of each group of terms and the mean length, over all documents. Every task sends one array of fixed
    size; `FAN_IN` of them at a time are summed in tasks."""
    size = (1 << GROUPS) + 2

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for b in batches:
            term, tf = (np.frombuffer(b"".join(x.as_buffer() for x in b[c]), kind) for c, kind in (("terms", np.uint32), ("times", np.uint16)))
            total[2:] += np.bincount(term[tf > 0] >> (32 - GROUPS), minlength=size - 2)
            total[:2] += len(b), int(tf.sum(dtype=np.int64)) + MORE * int((tf == 0).sum())
        yield pa.record_batch({"n": [pa.compress(total.tobytes(), codec="zstd", asbytes=True)]})

    def opened(x: bytes) -> np.ndarray:
        return np.frombuffer(pa.decompress(x, decompressed_size=8 * size, codec="zstd", asbytes=True), np.int64)

    def added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for b in batches:
            for x in b["n"]:
                total += opened(x.as_py())
        yield pa.record_batch({"n": [pa.compress(total.tobytes(), codec="zstd", asbytes=True)]})

    parts, sums = rows.select("terms", "times").rdd.getNumPartitions(), rows.select("terms", "times").mapInArrow(count, "n binary")
    while parts > FAN_IN:
        parts = -(-parts // FAN_IN)
        sums = sums.repartition(parts).mapInArrow(added, "n binary")
    total = np.zeros(size, np.int64)
    for x in sums.toArrow()["n"]:
        total += opened(x.as_py())
    docs, words, df = total[0], total[1], total[2:]
    return np.log1p((docs - df + 0.5) / (df + 0.5)), float(words) / max(1, int(docs))


class Shard:
    """An inverted index of one shard's open documents, with BM25 weights stored in the postings."""

    def __init__(self, terms: list[np.ndarray], times: list[np.ndarray], idf: np.ndarray, mean: float):
        doc = np.repeat(np.arange(len(terms)), [len(t) for t in terms])
        term, tf = np.concatenate(terms), np.concatenate(times).astype(np.int64)
        more = np.flatnonzero(tf == 0)
        if len(more):
            np.add.at(tf, np.maximum.accumulate(np.where(tf > 0, np.arange(len(tf)), 0))[more], MORE)
            doc, term, tf = doc[tf > 0], term[tf > 0], tf[tf > 0]
        length = np.bincount(doc, weights=tf, minlength=len(terms))[doc]
        weight = idf[term >> (32 - GROUPS)] * tf * (K1 + 1) / (tf + K1 * (1 - LENGTH_WEIGHT + LENGTH_WEIGHT * length / max(mean, 1e-9)))
        known, own = np.unique(term, return_inverse=True)  # the shard's terms by number
        self.own, self.cut, self.size = own, np.searchsorted(doc, np.arange(len(terms) + 1)), len(terms)
        order = np.argsort(own, kind="stable")
        self.doc, self.weight = doc[order], weight[order]
        self.start = np.searchsorted(own[order], np.arange(len(known) + 1))

    def scores(self, seed: int) -> np.ndarray:
        t = self.own[self.cut[seed] : self.cut[seed + 1]]
        first, n = self.start[t], self.start[t + 1] - self.start[t]
        at = np.repeat(first - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        return np.bincount(self.doc[at], self.weight[at], minlength=self.size)


def pack_shard(sizes: np.ndarray, shard: Shard, window: int = WINDOW) -> list[list[tuple[int, int, int]]]:
    """Sequences of (document, start, length). Each id once; all cuts at multiples of 64 of a document."""
    full = (sizes - 1) // window  # a document always keeps an open rest
    out = [[(d, k * window, window)] for d in np.flatnonzero(full).tolist() for k in range(int(full[d]))]
    start, left = full * window, sizes - full * window
    unused = np.ones(len(sizes), bool)
    by_length = np.argsort(-left, kind="stable").tolist()
    held: list[tuple[int, int, int]] = []
    cursor = 0
    while unused.any():
        while not unused[by_length[cursor]]:
            cursor += 1
        seed = by_length[cursor]
        unused[seed] = False
        held, space = [(seed, int(start[seed]), int(left[seed]))], window - int(left[seed])
        if space >= UNIT and unused.any():
            open_ = np.flatnonzero(unused)
            ranked = open_[np.lexsort((open_, -shard.scores(seed)[open_]))]
            fits = left[ranked]
            skipped = -1
            for d, n in zip(ranked.tolist(), fits.tolist(), strict=True):
                if n <= space:
                    held.append((d, int(start[d]), n))
                    unused[d] = False
                    space -= n
                elif skipped < 0:
                    skipped = d
                if space < UNIT or (skipped >= 0 and space < 2 * UNIT):
                    break
            if space >= UNIT and skipped >= 0:
                n = space // UNIT * UNIT
                held.append((skipped, int(start[skipped]), n))
                start[skipped] += n
                left[skipped] -= n
                space -= n
        out.append(held)
    if held and sum(n for _, _, n in held) <= window - UNIT:
        out[-1:] = split_tail(held, window)
    return out


def split_tail(pieces: list[tuple[int, int, int]], window: int) -> list[list[tuple[int, int, int]]]:
    """The same ids in sequences of power-of-two lengths as far as cuts at multiples of 64 allow, and one of what is left."""
    units = [(d, s + a, min(UNIT, n - a)) for d, s, n in pieces for a in range(0, n, UNIT)]
    whole, rest = [u for u in units if u[2] == UNIT], [u for u in units if u[2] < UNIT]
    out, at, size = [], 0, window // 2
    while size >= UNIT:
        if len(whole) - at >= size // UNIT:
            out.append(whole[at : at + size // UNIT])
            at += size // UNIT
        size //= 2
    tail: list[list[tuple[int, int, int]]] = [[]]
    for u in rest:
        if sum(x[2] for x in tail[-1]) + u[2] > window:
            tail.append([])
        tail[-1].append(u)
    out += [t for t in tail if t]
    merged = []
    for seq in out:
        joined: list[tuple[int, int, int]] = []
        for d, s, n in seq:
            if joined and joined[-1][0] == d and joined[-1][1] + joined[-1][2] == s:
                joined[-1] = (d, joined[-1][1], joined[-1][2] + n)
            else:
                joined.append((d, s, n))
        merged.append(joined)
    return merged


def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", tokenizer: str | None = None, end_id: int = 2, window: int = WINDOW, shard_docs: int = SHARD) -> DataFrame:
    """(key, start, length, ids_crc32, doc_tokens, sequence_id, offset): one row for each piece."""
    spark = docs.sparkSession
    if window % UNIT:
        raise ValueError(f"the window must be a multiple of {UNIT}")
    rows = measured(docs, key, text, tokenizer or default_tokenizer(), end_id)
    idf, mean = _statistics(rows)
    sent = spark.sparkContext.broadcast((idf, mean, _operators()))
    n = rows.count()
    dealt = rows.repartitionByRange(max(1, -(-n // (2 * shard_docs))), "route", "row").sortWithinPartitions("route", "row")
    kind = dict(rows.dtypes)["id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        idf, mean, tables = sent.value
        part, serial = TaskContext.get().partitionId(), 0
        held: list[pa.RecordBatch] = []

        def shard_of(t: pa.Table) -> Iterator[pa.RecordBatch]:
            nonlocal serial
            t = t.combine_chunks()
            sizes = t["n"].to_numpy()
            column = lambda c, kind: [np.frombuffer(x.as_buffer(), kind) for x in t[c].combine_chunks()]
            crcs, terms, times = column("crcs", np.uint32), column("terms", np.uint32), column("times", np.uint16)
            out: list[tuple] = []
            for seq in pack_shard(sizes, Shard(terms, times, idf, mean), window):
                offset = 0
                for d, s, length in seq:
                    units = crcs[d][s // UNIT : -(-(s + length) // UNIT)]
                    out.append((d, s, length, joined_crc(units, (length - 1) % UNIT + 1, tables), int(sizes[d]), (part << 40) + serial, offset))
                    offset += length
                serial += 1
            cols = list(zip(*out, strict=True))
            yield pa.RecordBatch.from_arrays([t["id"].combine_chunks().take(pa.array(cols[0])), *(pa.array(c, pa.int64()) for c in cols[1:])], names=["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

        for b in batches:
            while len(b):
                room = shard_docs - sum(map(len, held))
                held.append(b.slice(0, room))
                b = b.slice(min(room, len(b)))
                if sum(map(len, held)) == shard_docs:
                    yield from shard_of(pa.Table.from_batches(held))
                    held = []
        if held:
            yield from shard_of(pa.Table.from_batches(held))

    out = dealt.drop("row", "route").mapInArrow(run, f"id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
    return out.withColumnRenamed("id", key)


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents").select("doc_id", "text"))
