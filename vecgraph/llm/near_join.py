"""N-gram Jaccard self-join with a MinHash LSH forest and exact verification.

Texts with the same words in the same order form one copy class (two 64-bit hashes of them; empty texts too); only one text of a class is compared. Each of `trees`
prefix tries holds the classes under a signature of `depth` permuted minima of their five-word shingles. The tries are sorted runs of signatures,
not pointers: one pass groups the classes that share at least the shortest prefix that can be needed, and within such a run the longest common prefix of
two signatures is the depth at which their paths part.

The join descends to the full depth first: pairs that agree on a whole signature in some tree are verified exactly, then those that agree on one
minimum less, and so on. After each depth the recall so far is estimated from the similarities of the links found (a link of similarity s is met
with probability 1 - (1 - s^depth)^trees, and stands for the reciprocal number of links), with one unseen link at the threshold added; the prefixes are shortened until
the estimate reaches the target, at most to the depth at which every pair at the threshold is met with the target probability (`prefix_length`).

A pair is verified exactly once, at its greatest depth, in the first tree that reaches it. Runs are cut into tiles that grow with the square root of
the run, and a task gets two tiles at most: it counts the links of each member and joins linked members to the least of them, so a run of n near copies
sends each shingle set about sqrt(n) / 32 times and yields rows in proportion, never its n^2 pairs. Only members with a pair to verify there have their shingles sent.

The result has every row of the input: its class (connected component of links, named by the least id in it), its copy class, the number of copies and the number of
other rows within the threshold. No cap on partners, no pair dropped. Null texts count as empty; empty texts link only to each other. Rows with
a null id take part; ids of classes ignore nulls and are null only if all are. Copies of a row count as rows. An empty table gives an empty result."""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import connected_components, materialize, prepare, row_keys, table
from .words import MULTIPLIERS, minhash, mix, permutations, sequence_keys, shingles, slices, word_hashes

TREES, DEPTH, TARGET, TILE, BLOCK_SHINGLES, STEP = 16, 8, 0.9999, (1024, 16384, 32), 1 << 21, 1024


def meeting(similarity: float, length: int, trees: int) -> float:
    """Probability that a pair agrees on a prefix of this length in some tree."""
    return 1 - (1 - similarity**length) ** trees


def prefix_length(threshold: float, trees: int = TREES, depth: int = DEPTH, target: float = TARGET) -> int:
    """The longest prefix with which a pair at the threshold meets in at least one tree with the target probability."""
    for r in range(depth, 1, -1):
        if meeting(threshold, r, trees) >= target:
            return r
    return 1


def recall(found: dict[int, int], threshold: float, length: int, trees: int) -> float:
    """Estimated share of all links that prefixes of this length have met. found: links by thousandths of their similarity."""
    n = sum(found.values())
    missed = sum(c * (1 / meeting(s / 1000, length, trees) - 1) for s, c in found.items()) + 1 - meeting(threshold, length, trees)
    return n / (n + missed)


def signatures(texts: pa.Array, trees: int, depth: int) -> pa.StructArray:
    """Two hashes of all words in order, the number of shingles, and 16 bits of each minimum (trees by depth)."""
    perms, out = permutations(trees * depth), []
    for i, j in slices(texts):
        words, offsets = word_hashes(texts[i:j])
        sh, so, _ = shingles(words, offsets)
        count = np.diff(so)
        some = np.flatnonzero(count)
        bits = np.zeros((j - i, trees * depth), np.uint16)
        bits[some] = mix(minhash(sh, so[:-1][some], perms)) >> np.uint64(48)
        keys = [pa.array(sequence_keys(w, offsets).view(np.int64)) for w in (words, mix(words + MULTIPLIERS[7]))]
        out.append(pa.StructArray.from_arrays([*keys, pa.array(count), pa.array([x.tobytes() for x in bits], pa.binary())], ["key", "key2", "size", "sig"]))
    return pa.concat_arrays(out) if out else pa.array([], pa.struct([("key", pa.int64()), ("key2", pa.int64()), ("size", pa.int64()), ("sig", pa.binary())]))


def prefixes(sig: pa.Array, trees: int, depth: int, floor: int) -> np.ndarray:
    """(depth - floor + 1, rows, trees) labels of the prefixes of length floor to depth."""
    bits = np.frombuffer(b"".join(x.as_buffer() for x in sig), np.uint16).reshape(len(sig), trees, depth).astype(np.uint64)
    label, out = np.broadcast_to(np.arange(trees, dtype=np.uint64), bits.shape[:2]), []
    for d in range(depth):
        label = mix(label * MULTIPLIERS[0] + bits[:, :, d] + np.uint64(1))
        out.append(label)
    return np.stack(out[floor - 1 :])


def whole_groups(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables of whole groups of a stream sorted by key, and the groups' bounds; the group at the end of a batch waits for the next."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not len(b):
            continue
        if held and b[key][0].as_py() == held[-1][key][len(held[-1]) - 1].as_py() == b[key][len(b) - 1].as_py():
            held.append(b)
            continue
        t = pa.Table.from_batches([*held, b]).combine_chunks()
        k = t[key].to_numpy()
        bounds = np.concatenate([[0], np.flatnonzero(k[1:] != k[:-1]) + 1])
        if bounds[-1]:
            yield t.slice(0, int(bounds[-1])), bounds
        held = t.slice(int(bounds[-1])).to_batches()
    if held:
        t = pa.Table.from_batches(held).combine_chunks()
        yield t, np.array([0, len(t)])


def tiles(side: np.ndarray, cross: bool) -> Iterator[tuple[np.ndarray, np.ndarray, bool]]:
    """Members to compare with each other, some at a time: (rows, columns, whether both are the same)."""
    if cross:
        a, b = np.flatnonzero(side == side.min()), np.flatnonzero(side != side.min())
        yield from ((a[i : i + STEP], b[j : j + STEP], False) for i in range(0, len(a), STEP) for j in range(0, len(b), STEP))
    else:
        n = np.arange(len(side))
        yield from ((n[i : i + STEP], n[j : j + STEP], i == j) for i in range(0, len(n), STEP) for j in range(i, len(n), STEP))


def pair_depths(labels: np.ndarray, tree: int, rows: np.ndarray, columns: np.ndarray, same: bool, floor: int) -> np.ndarray:
    """Depth of each pair whose longest common prefix over all trees is found first in this tree; else 0."""
    deepest = labels[-1]
    open_ = np.triu(np.ones((len(rows), len(columns)), bool), 1) if same else np.ones((len(rows), len(columns)), bool)
    for t in range(tree):
        open_ &= deepest[rows, t][:, None] != deepest[columns, t][None, :]
    whole = open_ & (deepest[rows, tree][:, None] == deepest[columns, tree][None, :])
    out = np.where(whole, floor + len(labels) - 1, 0)
    a, b = np.nonzero(open_ & ~whole)
    for s in range(0, len(a), 1 << 15):
        x, y = a[s : s + (1 << 15)], b[s : s + (1 << 15)]
        length = (labels[:, rows[x]] == labels[:, columns[y]]).sum(axis=0)  # pairs by trees; prefixes are nested
        best = length.max(axis=1)
        out[x, y] = np.where((best > 0) & (length.argmax(axis=1) == tree), best + floor - 1, 0)
    return out


def verify(sets: list[np.ndarray], rows: np.ndarray, columns: np.ndarray, ok: np.ndarray, threshold: float) -> np.ndarray:
    """Jaccard similarity of the pairs in ok where it is at least the threshold, exactly; else 0."""
    size = np.array([len(s) for s in sets], np.int64)
    p, q = size[rows][:, None], size[columns][None, :]
    a, b = np.nonzero(ok & (np.minimum(p, q) >= threshold * np.maximum(p, q) - 1e-9))
    out = np.zeros(ok.shape)
    if not len(a):
        return out
    if len(a) <= 2 * (len(rows) + len(columns)):
        common = np.empty(len(a))
        for n, (i, j) in enumerate(zip(rows[a].tolist(), columns[b].tolist(), strict=True)):
            x, y = (sets[i], sets[j]) if len(sets[i]) <= len(sets[j]) else (sets[j], sets[i])
            at = np.searchsorted(y, x)
            common[n] = (y[np.minimum(at, len(y) - 1)] == x).sum()
    else:
        used = np.unique(np.concatenate([rows[a], columns[b]]))
        values, column = np.unique(np.concatenate([sets[i] for i in used]), return_inverse=True)
        row = np.repeat(np.arange(len(used)), size[used])
        shared = np.bincount(column, minlength=len(values)) > 1
        number = np.cumsum(shared) - 1
        keep = shared[column]
        row, column = row[keep], number[column[keep]]
        order = np.argsort(column, kind="stable")
        row, column = row[order], column[order]
        place = np.full(len(sets), -1)
        place[used] = np.arange(len(used))
        left, right = place[rows], place[columns]
        total, width = np.zeros(ok.shape, np.float32), 4096
        for lo in range(0, int(shared.sum()), width):
            s, e = np.searchsorted(column, [lo, lo + width])
            x = np.zeros((len(used) + 1, width), np.float32)
            x[row[s:e], column[s:e] - lo] = 1
            total += x[left] @ x[right].T  # members without a pair have the empty last row
        common = total[a, b].astype(np.float64)
    either = size[rows[a]] + size[columns[b]] - common
    out[a, b] = np.where(common >= threshold * either - 1e-9, common / either, 0)
    return out


def groups_of(t: pa.Table, bounds: np.ndarray) -> list[tuple[int, int]]:
    ends = np.append(bounds[1:], len(t)) if bounds[-1] != len(t) else bounds[1:]
    return [(s, e) for s, e in zip(bounds[: len(ends)].tolist(), ends.tolist(), strict=True) if e - s > 1]


def to_verify(trees: int, depth: int, floor: int):
    """Members with pairs to verify in their group, and the depths of those as bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t, bounds in whole_groups(batches, "g"):
            depths = np.zeros(len(t), np.int64)
            for s, e in groups_of(t, bounds):
                part = t.slice(s, e - s)
                labels = prefixes(part["sig"].combine_chunks(), trees, depth, floor)
                for rows, columns, same in tiles(part["side"].to_numpy(), part["cross"][0].as_py()):
                    found = pair_depths(labels, part["tree"][0].as_py(), rows, columns, same, floor)
                    for d in range(floor, depth + 1):
                        here = found == d
                        if here.any():
                            depths[s + rows[here.any(axis=1)]] |= 1 << d
                            depths[s + columns[here.any(axis=0)]] |= 1 << d
            yield from t.append_column("depths", pa.array(depths)).filter(pa.array(depths > 0)).to_batches()

    return run


def joined(threshold: float, trees: int, depth: int, floor: int, at: int):
    """Verifies the pairs of one depth. Rows (key, links, root); rows with a key below 0 count links by similarity: -1 - thousandths."""
    schema = pa.schema([("key", pa.int64()), ("links", pa.int64()), ("root", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t, bounds in whole_groups(batches, "g"):
            key, copies, sets = t["key"].to_numpy(), t["copies"].to_numpy(), t["shingles"].combine_chunks()
            out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
            for s, e in groups_of(t, bounds):
                part = t.slice(s, e - s)
                labels = prefixes(part["sig"].combine_chunks(), trees, depth, floor)
                own, k, c = [np.frombuffer(sets[i].as_buffer(), np.uint64) for i in range(s, e)], key[s:e], copies[s:e]
                for rows, columns, same in tiles(part["side"].to_numpy(), part["cross"][0].as_py()):
                    ok = pair_depths(labels, part["tree"][0].as_py(), rows, columns, same, floor) == at
                    similar = verify(own, rows, columns, ok, threshold) if ok.any() else None
                    if similar is None or not similar.any():
                        continue
                    linked = similar > 0
                    steps, n = np.unique((similar[linked] * 1000 + 1e-9).astype(np.int64), return_counts=True)
                    out.append((-1 - steps, n, np.zeros(len(n), np.int64)))
                    left, right, last = k[rows].copy(), k[columns].copy(), None
                    while last is None or (last[0] != left).any() or (last[1] != right).any():  # least key of the component within the tile
                        last = left.copy(), right.copy()
                        most = np.iinfo(np.int64).max
                        left = np.minimum(left, np.where(linked, right[None, :], most).min(axis=1))
                        right = np.minimum(right, np.where(linked, left[:, None], most).min(axis=0))
                        if same:
                            left = right = np.minimum(left, right)
                    for at_, r, n in ((rows, left, linked @ c[columns]), (columns, right, linked.T @ c[rows])):
                        some = np.flatnonzero(n)
                        out.append((k[at_][some], n[some], r[some]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).astype(np.int64)) for x in zip(*out, strict=True)], schema=schema)

    return run


def near_classes(docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = 0.8, trees: int = TREES, depth: int = DEPTH, target: float = TARGET) -> DataFrame:
    """(key, class_id, copy_id, n_copies, n_links) for every row, plus _k1 and _k2, the row's keys, and class_key, the root of its component: classes
    whose rows share an id have one class_id, but never one class_key."""
    prepare(docs.sparkSession)
    floor = prefix_length(threshold, trees, depth, target)
    docs = docs.select(F.col(key).alias("id"), F.col(text).cast("string").alias("text"))
    names = row_keys("id", "text")

    @F.arrow_udf("struct<key long, key2 long, size long, sig binary>")
    def signed(texts: pa.Array) -> pa.Array:
        return signatures(texts, trees, depth)

    @F.arrow_udf("array<long>")
    def roots(sig: pa.Array) -> pa.Array:
        labels = prefixes(sig, trees, depth, floor)[0]
        return pa.ListArray.from_arrays(pa.array(np.arange(0, labels.size + 1, trees, dtype=np.int32)), pa.array(labels.reshape(-1).view(np.int64)))

    rows = materialize(docs.select("id", *names, signed(F.col("text")).alias("s")).select("id", "_k1", "_k2", F.col("s.key").alias("key1"), "s.key2", "s.size", "s.sig"), "near-rows")
    classes = rows.groupBy("key1", "key2").agg(F.count("*").alias("copies"), F.min("id").alias("copy_id"), F.min(F.struct("_k1", "_k2")).alias("row"), F.first("size").alias("size"), F.first("sig").alias("sig"))
    classes = materialize(classes.withColumn("key", F.monotonically_increasing_id()), "near-classes")  # keys are fixed once written

    met = classes.where("size > 0").select("key", "size", F.posexplode(roots("sig")).alias("tree", "label"))
    runs = met.groupBy("tree", "label").agg(F.count("*").alias("n"), F.sum("size").alias("total")).where("n > 1")
    least, most, root = TILE
    tile = F.greatest(F.lit(least), F.least(F.lit(most), F.lit(root) * F.sqrt("n")))
    runs = runs.select("tree", "label", F.greatest(F.ceil(F.col("n") / tile), F.ceil(F.col("total") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
    own = met.select("key", "tree", "label").join(runs, ["tree", "label"])
    own = own.withColumn("side", F.pmod(F.xxhash64("key", "tree"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    pairs = own.select("key", "tree", "label", "side", other).select("key", "tree", "side", (F.col("side") != F.col("other")).alias("cross"), F.xxhash64("tree", "label", F.least("side", "other"), F.greatest("side", "other")).alias("g"))
    tries = pairs.join(classes.select("key", "sig", "copies", "row"), "key").select("g", "tree", "side", "cross", "key", "copies", "row", "sig")
    columns = "g long, tree int, side int, cross boolean, key long, copies long, row struct<_k1 long, _k2 long>, sig binary, depths long"
    todo = materialize(tries.repartition("g").sortWithinPartitions("g").mapInArrow(to_verify(trees, depth, floor), columns), "near-todo")

    needed = todo.select("key", "row._k1", "row._k2").distinct()
    texts = docs.withColumns({"_k1": names[0], "_k2": names[1]}).join(needed.select("_k1", "_k2"), ["_k1", "_k2"], "left_semi")

    @F.arrow_udf("binary")
    def sets(texts: pa.Array) -> pa.Array:
        out: list[bytes] = []
        for i, j in slices(texts):
            sh, so, _ = shingles(*word_hashes(texts[i:j]))
            out += [np.unique(sh[a:b]).tobytes() for a, b in zip(so[:-1], so[1:], strict=True)]
        return pa.array(out, pa.binary())

    # copies of a whole row have equal keys; one of them is enough
    held = texts.dropDuplicates(["_k1", "_k2"]).join(needed, ["_k1", "_k2"]).select("key", sets(F.col("text")).alias("shingles"))
    held = materialize(held, "near-sets")
    found: dict[int, int] = {}
    parts = []
    for at in range(depth, floor - 1, -1):
        ready = todo.where(F.col("depths").bitwiseAND(1 << at) > 0).join(held, "key").select("g", "tree", "side", "cross", "key", "copies", "sig", "shingles")
        parts.append(materialize(ready.repartition("g").sortWithinPartitions("g").mapInArrow(joined(threshold, trees, depth, floor, at), "key long, links long, root long"), "near-links"))
        for r in parts[-1].where("key < 0").groupBy("key").agg(F.sum("links").alias("n")).collect():
            found[-1 - r["key"]] = found.get(-1 - r["key"], 0) + r["n"]
        if recall(found, threshold, at, trees) >= target:
            break
    links = functools.reduce(DataFrame.unionByName, parts).where("key >= 0")

    counts = links.groupBy("key").agg(F.sum("links").alias("links"))
    component = connected_components(links, "key", "root", "near")
    named = classes.join(component, classes["key"] == component["node"], "left").select("key1", "key2", "key", "copies", "copy_id", F.coalesce("root", "key").alias("root"))
    least_id = named.groupBy("root").agg(F.min("copy_id").alias("class_id"))
    named = named.join(least_id, "root").join(counts, "key", "left").select("key1", "key2", F.col("root").alias("class_key"), "class_id", "copy_id", F.col("copies").alias("n_copies"), (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))
    return rows.select(F.col("id").alias(key), "_k1", "_k2", "key1", "key2").join(named, ["key1", "key2"]).drop("key1", "key2")


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = 0.8) -> DataFrame:
    """One row of each class: that of the least id (a null id only where no id is known), of rows with that id the one whose keys are least,
    and of rows repeated with other columns the least of those. Columns are those of docs."""
    names = row_keys(key, text)
    found = near_classes(docs, key, text, threshold)
    chosen = found.groupBy("class_key").agg(F.min(F.struct(F.col(key).isNull().alias("none"), F.col(key).alias("id"), "_k1", "_k2")).alias("x")).select("x._k1", "x._k2")
    kept = docs.withColumns({"_k1": names[0], "_k2": names[1]}).join(chosen, ["_k1", "_k2"], "left_semi")
    return kept.groupBy("_k1", "_k2").agg(F.min(F.struct(*(f"`{c}`" for c in docs.columns))).alias("x")).select("x.*")


def op10_near_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return near_classes(docs).select("doc_id", "class_id", "copy_id", "n_copies", "n_links", "class_key")
