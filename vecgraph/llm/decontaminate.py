"""Benchmark decontamination: containment of short test items in long documents by size-partitioned MinHash, verified exactly.

Containment of an item in a document is the share of the item's five-word shingles that the document has. A MinHash
of a whole long document says nothing about a short item, so sizes are partitioned on the items' side: items of 2^c to 2^(c+1) - 1
shingles are sought in windows of 2^(c+2) shingles that advance by half their length, so that any passage of the item's length lies
inside a window and their Jaccard similarity is bounded from below. A window and an item that agree in one of `hashes` permuted minima are a candidate;
the item is then compared with all shingles of the whole document. Items are split in blocks of `item_block`, which bounds what is broadcast; each
block is one pass over the documents, nothing of which is shuffled.

Null texts count as empty and contain nothing; items without a word match nothing; an item of one to four words is one shingle and matches only a text that
consists of those words. Repeated items and repeated documents are each reported. Empty tables give an empty result."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.core.broadcast import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import prepare, row_keys, table
from .words import minhash, permutations, shingles, slices, word_hashes

HASHES, ITEM_BLOCK = 48, 20_000


class ItemIndex:
    """The items of one block by size class: sorted permuted minima of each hash, and every item's shingles."""

    def __init__(self, ids: list, texts: list[str | None], hashes: int = HASHES):
        self.perms, self.classes = permutations(hashes, 21), {}
        sh, so, _ = shingles(*word_hashes(pa.array(texts, pa.string())))
        self.ids, self.sets = ids, [np.unique(sh[a:b]) for a, b in zip(so[:-1], so[1:], strict=True)]
        size = np.array([len(s) for s in self.sets], np.int64)
        for c in sorted({int(n).bit_length() - 1 for n in size if n}):
            at = np.flatnonzero((size >= 1 << c) & (size < 2 << c))
            own = np.concatenate([self.sets[i] for i in at])
            minima = minhash(own, np.concatenate([[0], np.cumsum(size[at])[:-1]]), self.perms)
            order = np.argsort(minima, axis=0, kind="stable")
            self.classes[c] = (np.take_along_axis(minima, order, axis=0), at[order])

    def search(self, texts: pa.Array, threshold: float) -> Iterator[tuple[int, int, int]]:
        """(text number, item number, shared shingles) of every containment at the threshold."""
        sh, so, _ = shingles(*word_hashes(texts))
        count = np.diff(so)
        some = np.flatnonzero(count)
        if not len(some):
            return
        plans = {}
        for c in self.classes:
            step = 2 << c
            blocks = -(-count[some] // step)
            doc = np.repeat(some, blocks)
            place = np.arange(len(doc)) - np.repeat(np.cumsum(blocks) - blocks, blocks)
            plans[c] = (doc, so[doc] + place * step, np.append(doc[1:] == doc[:-1], False))
        found: list[np.ndarray] = []
        for k, m in enumerate(self.perms):
            values = sh * m
            for c, (doc, starts, followed) in plans.items():
                low = np.minimum.reduceat(values, starts)
                low[:-1] = np.where(followed[:-1], np.minimum(low[:-1], low[1:]), low[:-1])
                keys, items = self.classes[c][0][:, k], self.classes[c][1][:, k]
                first = np.searchsorted(keys, low)
                hit = np.flatnonzero(keys[np.minimum(first, len(keys) - 1)] == low)
                if len(hit):
                    n = np.searchsorted(keys, low[hit], "right") - first[hit]
                    at = np.repeat(first[hit], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                    found.append(np.repeat(doc[hit], n) * len(self.sets) + items[at])
        last, own = -1, np.zeros(0, np.uint64)
        for pair in np.unique(np.concatenate(found)).tolist() if found else []:
            d, i = divmod(pair, len(self.sets))
            if d != last:
                last, own = d, np.unique(sh[so[d] : so[d + 1]])
            at = np.minimum(np.searchsorted(own, self.sets[i]), len(own) - 1)
            shared = int((own[at] == self.sets[i]).sum())
            if shared >= threshold * len(self.sets[i]) - 1e-9:
                yield d, i, shared


def contained(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", threshold: float = 0.8, item_block: int = ITEM_BLOCK, names: bool = False) -> DataFrame:
    """(key, item_key, n_shared, n_item, containment) of all pairs at the threshold; names adds _k1 and _k2, the row keys of the document."""
    spark = docs.sparkSession
    prepare(spark)
    rows = docs.select(F.col(key).alias("id"), *row_keys(key, text), F.col(text).cast("string").alias("text"))
    kind = dict(items.select(F.col(item_key).alias("i")).dtypes)["i"]
    total = items.count()
    out = None
    for b in range(max(1, -(-total // item_block))):
        own = items.select(F.col(item_key).alias("i"), F.col(item_text).cast("string").alias("t"))
        if total > item_block:
            own = own.where(F.pmod(F.xxhash64("i", "t"), F.lit(-(-total // item_block))) == b)
        got = own.collect()
        sent = spark.sparkContext.broadcast(ItemIndex([r["i"] for r in got], [r["t"] for r in got]))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            index = sent.value
            for batch in batches:
                for i, j in slices(batch["text"]):
                    part = batch.slice(i, j - i)
                    hits = list(index.search(part["text"], threshold))
                    if hits:
                        at = pa.array([h[0] for h in hits])
                        size = np.array([len(index.sets[h[1]]) for h in hits])
                        shared = np.array([h[2] for h in hits])
                        yield pa.RecordBatch.from_arrays([part["id"].take(at), part["_k1"].take(at), part["_k2"].take(at), pa.array([index.ids[h[1]] for h in hits]), pa.array(shared), pa.array(size), pa.array(shared / size)], names=["id", "_k1", "_k2", "item", "shared", "size", "containment"])

        found = rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, _k1 long, _k2 long, item {kind}, shared long, size long, containment double")
        out = found if out is None else out.unionByName(found)
    out = out.select(F.col("id").alias(key), "_k1", "_k2", F.col("item").alias(item_key), F.col("shared").alias("n_shared"), F.col("size").alias("n_item"), "containment")
    return out if names else out.drop("_k1", "_k2")


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return contained(docs, table(spark, sf_dir, "benchmark").select("item_id", "text"))


def flag_contaminated(docs: DataFrame, items: DataFrame, text: str = "text", item_text: str = "text", threshold: float = 0.8, item_block: int = ITEM_BLOCK, out: str = "contaminated") -> DataFrame:
    """docs with a boolean column: whether some item is contained at the threshold. One pass, no shuffle; each block of items is one more function over the text."""
    prepare(docs.sparkSession)
    total, flags = items.count(), F.lit(False)
    blocks = max(1, -(-total // item_block))
    for b in range(blocks):
        own = items.select(F.col(item_text).cast("string").alias("t"))
        got = (own.where(F.pmod(F.xxhash64("t"), F.lit(blocks)) == b) if blocks > 1 else own).collect()
        sent = docs.sparkSession.sparkContext.broadcast(ItemIndex(list(range(len(got))), [r["t"] for r in got]))

        flags = flags | _hits(sent, threshold)(F.col(text).cast("string"))
    return docs.withColumn(out, flags)


def _hits(sent: Broadcast, threshold: float) -> Callable:
    @F.arrow_udf("boolean")
    def hit(texts: pa.Array) -> pa.Array:
        found = np.zeros(len(texts), bool)
        for i, j in slices(texts):
            found[[i + d for d, _, _ in sent.value.search(texts[i:j], threshold)]] = True
        return pa.array(found)

    return hit


_WORDS = "regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9[:^ascii:]]+')"
_SHINGLES = "unnest(CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS s"
SQL = f"""
WITH d AS (SELECT r, doc_id, {_SHINGLES} FROM (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS w FROM documents)),
i AS (SELECT r, item_id, {_SHINGLES} FROM (SELECT row_number() OVER () AS r, item_id, {_WORDS} AS w FROM benchmark)),
n AS (SELECT r, count(*) AS n_item FROM i GROUP BY r),
met AS (SELECT d.r AS x, d.doc_id, i.r AS y, i.item_id, count(*) AS n_shared FROM d JOIN i ON d.s = i.s GROUP BY ALL)
SELECT doc_id, item_id, n_shared, n_item, n_shared / n_item AS containment FROM met JOIN n ON n.r = y WHERE n_shared >= 0.8 * n_item - 1e-9
"""
