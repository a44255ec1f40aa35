"""Language identification with bit-sliced Bloom filters of n-grams.

One table of slots holds all filters: bit l of a slot belongs to the filter of language l, so one lookup of an n-gram
(`HASHES` slots, ANDed) returns the set of all languages that contain it. A text's n-grams are counted per language; the
counts are corrected for each filter's own false-positive rate, and the largest wins. An n-gram is four bytes of UTF-8
text in lower case in which every run of non-letters is one blank.

A filter holds the n-grams whose share in its language's text is at least `MIN_SHARE` and at least `RELATIVE` of the largest
share in any language, which keeps words quoted from another language out. The classifier is fitted on a bounded sample of
the labelled rows: about `per_language` documents for each language, chosen by a hash of the id, whole texts.

Null texts and texts without any letter are `und` with score 0. A text none of whose n-grams is known gets the commonest
learned language and score 0; ties go to the language first in order. Rows with a null language or null text are not
learned from. Every row is predicted for itself, copies alike; columns of the input pass through. With nothing to learn from, every text
is `und`."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_bucket, prepare, table
from .words import _bytes, slices

SLOTS_LOG2, HASHES = 20, 2
MIN_SHARE, RELATIVE = 3e-6, 0.3
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True
_MULTIPLIERS = [0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F]


def grams(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All n-grams of the texts as numbers, and the offsets of each text's n-grams. Those without a letter in the middle are left out."""
    data, offsets = _bytes(pc.utf8_lower(texts))
    n = len(data)
    inside = _LETTER[data]
    keep = inside.copy()
    keep[1:] |= inside[:-1]
    firsts = offsets[:-1][np.diff(offsets) > 0]
    keep[firsts] = True
    flat = np.where(inside, data, 32).astype(np.uint32)[keep]
    place = np.concatenate([[0], np.cumsum(keep)])[offsets] if n else np.zeros(len(offsets), np.int64)
    count = np.diff(place)
    if len(flat) < 4:
        return np.zeros(0, np.uint32), np.zeros(len(offsets), np.int64)
    g = flat[:-3] | flat[1:-2] << 8 | flat[2:-1] << 16 | flat[3:] << 24
    ok = np.arange(len(g)) < (np.repeat(place[1:] - 3, count)[: len(g)])
    return g[ok], np.concatenate([[0], np.cumsum(np.maximum(count - 3, 0))])


def slots(g: np.ndarray) -> list[np.ndarray]:
    return [((g * np.uint32(m)) >> np.uint32(32 - SLOTS_LOG2)).astype(np.int64) for m in _MULTIPLIERS[:HASHES]]


class LanguageFilters:
    """The fitted table: uint64 words, 64 languages in each column."""

    def __init__(self, languages: list[str], weights: list[float], pairs: list[tuple[int, int]]):
        """pairs: (language number, n-gram)."""
        self.languages = languages
        self.default = int(np.argmax(weights)) if weights else 0
        self.bits = np.zeros((max(1, -(-len(languages) // 64)), 1 << SLOTS_LOG2), np.uint64 if len(languages) > 8 else np.uint8)
        for k in range(len(languages)):
            own = np.array([g for i, g in pairs if i == k], np.uint32) if not isinstance(pairs, dict) else pairs.get(k, np.zeros(0, np.uint32))
            for s in slots(own):
                self.bits[k // 64][s] |= self.bits.dtype.type(1 << (k % 64))
        fill = [float(((self.bits[k // 64] >> self.bits.dtype.type(k % 64)) & self.bits.dtype.type(1)).mean()) for k in range(len(languages))]
        self.false_positive = np.array([f**HASHES for f in fill])

    @classmethod
    def fit(cls, docs: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", per_language: int = 4000) -> LanguageFilters:
        spark = docs.sparkSession
        prepare(spark)
        rows = docs.select(F.col(key).alias("k"), F.col(text).alias("text"), F.col(lang).alias("lang")).where("text is not null and lang is not null")
        counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
        languages = sorted(counts)
        if not languages:
            return cls([], [], [])
        share = F.create_map(*[F.lit(x) for k in languages for x in (k, min(1.0, per_language / counts[k]))])
        sample = rows.where(F.pmod(F.xxhash64(F.lit(5), "k"), F.lit(1 << 30)) < share[F.col("lang")] * (1 << 30))

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for name in pc.unique(b["lang"]).to_pylist():
                    own = b["text"].filter(pc.equal(b["lang"], name))
                    found = [np.unique(grams(own[i:j])[0], return_counts=True) for i, j in slices(own)]
                    for g, n in found:
                        yield pa.record_batch({"lang": pa.array([name] * len(g), pa.string()), "g": g.astype(np.int64), "n": n.astype(np.int64)})

        seen = sample.select("lang", "text").mapInArrow(count, "lang string, g long, n long").groupBy("lang", "g").agg(F.sum("n").alias("n"))
        from .common import materialize

        seen = materialize(seen, "language-grams")
        totals = {r["lang"]: r["n"] for r in seen.groupBy("lang").agg(F.sum("n").alias("n")).collect()}
        total = F.create_map(*[F.lit(x) for k in languages for x in (k, float(totals.get(k, 1)))])
        rated = seen.withColumn("rate", F.col("n") / total[F.col("lang")]).where(F.col("rate") >= MIN_SHARE)
        best = rated.groupBy("g").agg(F.max("rate").alias("best"))
        chosen = rated.join(best, "g").where(F.col("rate") >= RELATIVE * F.col("best")).select("lang", "g").toPandas()
        return cls(languages, [counts[k] for k in languages], {i: chosen.loc[chosen["lang"] == k, "g"].to_numpy().astype(np.uint32) for i, k in enumerate(languages)})

    def decide(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Language number (-1: und) and score of each text."""
        lang, score = np.full(len(texts), -1), np.zeros(len(texts))
        if not self.languages:
            return lang, score
        for i, j in slices(texts):
            g, offsets = grams(texts[i:j])
            total, hits = np.diff(offsets), np.zeros((j - i, len(self.languages)))
            some = np.flatnonzero(total > 0)
            if len(some):
                at = slots(g)
                for w, column in enumerate(self.bits):
                    found = column[at[0]]
                    for s in at[1:]:
                        found &= column[s]
                    for k in range(64 * w, min(64 * w + 64, len(self.languages))):
                        one = (found >> found.dtype.type(k % 64)) & found.dtype.type(1)
                        hits[some, k] = np.add.reduceat(one, offsets[:-1][some], dtype=np.int64)
            true = np.maximum(0, hits - self.false_positive * total[:, None]) / (1 - np.minimum(self.false_positive, 0.999))
            all_hits = true.sum(axis=1)
            lang[i:j] = np.where(all_hits > 0, true.argmax(axis=1), self.default)
            score[i:j] = np.where(all_hits > 0, true.max(axis=1) / np.maximum(all_hits, 1e-300), 0)
        letters = pc.fill_null(pc.match_substring_regex(texts, r"\pL"), False).to_numpy(zero_copy_only=False)
        return np.where(letters, lang, -1), np.where(letters, score, 0.0)

    def predict(self, docs: DataFrame, text: str = "text") -> DataFrame:
        """docs with lang_pred and score (columns of these names in docs are replaced)."""
        prepare(docs.sparkSession)
        model = docs.sparkSession.sparkContext.broadcast(self)

        @F.arrow_udf("struct<lang_pred string, score double>")
        def predicted(texts: pa.Array) -> pa.Array:
            m = model.value
            lang, score = m.decide(texts.cast(pa.string()))
            names = pa.array([*m.languages, "und"], pa.string())
            return pa.StructArray.from_arrays([names.take(pa.array(np.where(lang < 0, len(m.languages), lang))), pa.array(score)], ["lang_pred", "score"])

        return docs.withColumn("_p", predicted(F.col(text))).withColumns({"lang_pred": F.col("_p.lang_pred"), "score": F.col("_p.score")}).drop("_p")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang").withColumn("held_out", crc_bucket("doc_id", 4) == 2)
    model = LanguageFilters.fit(docs.where(~F.col("held_out")))
    return model.predict(docs.select("doc_id", "text", "held_out")).select("doc_id", "held_out", "lang_pred", "score")
