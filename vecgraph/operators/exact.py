"""Exact search: truth by linear scan, range search, filtered search, and joins built on them.

The query set is answered in blocks of at most BLOCK_BYTES. A set of one block is collected and broadcast; a larger one is first written as a table cut by hash,
and its blocks are fetched, broadcast and answered one after another, so that the driver holds two blocks at most, whatever the size of the set; their answers are a table in the
shared folder. Every task keeps its own k best for each query, and only those are
shuffled. Squared distances fold over the dimensions in order, so that equal vectors tie exactly; ties go to the smaller id."""

from __future__ import annotations

import itertools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..sources.tables import shared_dir
from .codecs import matrix

BLOCK_BYTES = 64 << 20
TASK_PAIRS = 1 << 21  # distances of a task at once; it holds some five arrays of them
PAIR_BLOCK = 1 << 16  # pairs whose sums fold at once, in the nearest cache
BOX_ROWS, LEAF = 1 << 18, 512  # rows of a task that are split into boxes at once, rows of a box
NEAR = "query_id long, vec_id long, dist double"


def top_k(rows: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, vec_id, dist): the k nearest of (query_id, vec_id, dist). The filter on the rank lets Spark keep k rows of each group before the shuffle."""
    w = W.partitionBy("query_id").orderBy("dist", "vec_id")
    return rows.select("query_id", "vec_id", "dist").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "dist")


def query_blocks(queries: DataFrame, row_bytes: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, vectors) of the queries, a block of about BLOCK_BYTES at a time; each is fetched only when it is asked for."""
    parts = -(-queries.count() * row_bytes // BLOCK_BYTES)
    if parts <= 1:
        cut = [queries]
    else:
        path = shared_dir(queries.sparkSession, "query-blocks")
        queries.select("vec_id", "vec", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).alias("block")).write.partitionBy("block").parquet(path)
        held = queries.sparkSession.read.schema("vec_id long, vec array<double>, block long").parquet(path)
        cut = (held.where(F.col("block") == b) for b in range(parts))
    for part in cut:
        got = part.select("vec_id", "vec").toArrow()
        if got.num_rows:
            yield got["vec_id"].to_numpy(), matrix(got["vec"])


def in_blocks(base: DataFrame, queries: DataFrame, row_bytes: int, scan: Callable, schema: str, finish: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """finish(rows that scan(block, batches of base) finds), for each block of the queries."""
    spark = base.sparkSession

    def answered(block: tuple) -> tuple:
        sent = spark.sparkContext.broadcast(block)
        return sent, finish(base.mapInArrow(lambda batches: scan(sent.value, batches), schema))

    blocks = query_blocks(queries, row_bytes)
    first, second = next(blocks, None), next(blocks, None)
    if first is None:
        return finish(spark.createDataFrame([], schema))
    if second is None:
        return answered(first)[1]
    path, like = shared_dir(spark, "block-answers"), None
    for block in itertools.chain((first, second), blocks):
        sent, found = answered(block)
        like = found.schema
        found.write.mode("append").parquet(path)
        sent.destroy()
    return spark.read.schema(like).parquet(path)


def near_in_task(ids: np.ndarray, x: np.ndarray, qids: np.ndarray, q: np.ndarray, k: int, exclude: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query_id, vec_id, squared distance) of the k nearest rows for each query. A matrix product picks rows that can be among them; folded sums decide."""
    approx = (q * q).sum(1)[:, None] - 2 * (q @ x.T) + (x * x).sum(1)[None, :]
    if exclude:
        approx[qids[:, None] == ids[None, :]] = np.inf
    kk = min(k, len(ids))
    bound = np.partition(approx, kk - 1, axis=1)[:, kk - 1]
    slack = 1e-9 * (1 + np.abs(np.where(np.isfinite(bound), bound, 0)) + (q * q).sum(1))
    r, c = np.nonzero((approx <= (bound + slack)[:, None]) & np.isfinite(approx))
    acc = np.zeros(len(r))
    for d in range(q.shape[1]):
        diff = q[r, d] - x[c, d]
        acc += diff * diff
    order = np.lexsort((ids[c], acc, r))
    r, c, acc = r[order], c[order], acc[order]
    place = np.arange(len(r)) - np.searchsorted(r, r)
    keep = place < k
    return qids[r[keep]], ids[c[keep]], acc[keep]


def exact_knn(base: DataFrame, queries: DataFrame, k: int = 10, self_match: str = "exclude") -> DataFrame:
    """(query_id, rank, vec_id, dist) with true distances. A base row with the query's own id counts only with self_match='include'."""
    exclude = self_match == "exclude"
    dim = len((queries.select("vec").first() or [[0]])[0])

    def nearest(block: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q = block
        best = None
        for b in batches:
            if len(b):
                ids, x = b["vec_id"].to_numpy(), matrix(b["vec"])
                step = max(1, TASK_PAIRS // len(b))
                for s in range(0, len(q), step):
                    found = near_in_task(ids, x, qids[s : s + step], q[s : s + step], k, exclude)
                    best = found if best is None else tuple(np.concatenate(y) for y in zip(best, found, strict=True))
                order = np.lexsort((best[1], best[2], best[0]))
                sorted_q = best[0][order]
                order = order[np.arange(len(order)) - np.searchsorted(sorted_q, sorted_q) < k]
                best = tuple(y[order] for y in best)
        if best is not None:
            yield pa.record_batch({"query_id": best[0], "vec_id": best[1], "dist": best[2]})

    return in_blocks(base.select("vec_id", "vec"), queries, 8 * dim, nearest, NEAR, lambda found: top_k(found, k)).withColumn("dist", F.sqrt("dist"))


class Boxes:
    """Rows split at medians into leaves of at most LEAF rows, each with its bounding box."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        depth = max(0, (-(-len(x) // LEAF) - 1).bit_length())
        size = -(-len(x) // (1 << depth)) << depth
        at = np.concatenate([np.arange(len(x)), np.zeros(size - len(x), np.int64)])  # filled up with the first row, whose copies never count
        real = np.arange(size) < len(x)
        for level in range(depth):
            node = at.reshape(1 << level, -1)
            spread = x[node]
            widest = (spread.max(axis=1) - spread.min(axis=1)).argmax(axis=1)
            half = node.shape[1] // 2
            order = np.argpartition(np.take_along_axis(spread, widest[:, None, None], 2)[:, :, 0], half, axis=1)
            at, real = (np.take_along_axis(y.reshape(node.shape), order, 1).ravel() for y in (at, real))
        self.at, self.real = (y.reshape(1 << depth, -1) for y in (at, real))
        self.ids = ids[self.at]
        self.x = np.ascontiguousarray(np.moveaxis(x[self.at], 2, 0))  # by dimension
        self.low, self.high = self.x.min(axis=2), self.x.max(axis=2)

    def bounds(self, q: np.ndarray) -> np.ndarray:
        """(queries, leaves): squared distances to the boxes."""
        out = np.zeros((len(q), self.low.shape[1]))
        for d in range(q.shape[1]):
            gap = np.maximum(np.maximum(self.low[d][None, :] - q[:, d, None], q[:, d, None] - self.high[d][None, :]), 0)
            out += gap * gap
        return out

    def within(self, qids: np.ndarray, q: np.ndarray, row: np.ndarray, leaf: np.ndarray, limit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, id, squared distance) of the rows of the leaves up to each query's limit, its own id left out."""
        out = []
        for s in range(0, len(row), 1024):
            r, c = row[s : s + 1024], leaf[s : s + 1024]
            acc = np.zeros((len(r), self.x.shape[2]))
            for d in range(q.shape[1]):
                diff = q[r, d, None] - self.x[d][c]
                acc += diff * diff
            i, j = np.nonzero((acc <= limit[r, None]) & self.real[c] & (self.ids[c] != qids[r, None]))
            out.append((r[i], self.ids[c[i], j], acc[i, j]))
        return tuple(np.concatenate(y) for y in zip(*out, strict=True)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))


def boxed_knn(base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """exact_knn for few dimensions, a query's own id left out: every task splits BOX_ROWS rows at a time into boxes, and a query measures only rows of boxes that are not farther than
    the k-th best it has so far."""
    dim = len((queries.select("vec").first() or [[0]])[0])

    def nearest(block: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q = block
        best_id, best = np.full((len(q), k), -1), np.full((len(q), k), np.inf)

        def keep(start: int, found: tuple) -> None:
            r, ids, dist = found
            rows = np.unique(r)
            old = np.repeat(rows, k)
            r, ids, dist = np.concatenate([r, old]), np.concatenate([ids, best_id[start + rows].ravel()]), np.concatenate([dist, best[start + rows].ravel()])
            order = np.lexsort((ids, dist, r))
            r, ids, dist = r[order], ids[order], dist[order]
            place = np.arange(len(r)) - np.searchsorted(r, r)
            some = place < k
            best_id[start + r[some], place[some]], best[start + r[some], place[some]] = ids[some], dist[some]

        def visit(held: list) -> None:
            boxes = Boxes(np.concatenate([b["vec_id"].to_numpy() for b in held]), np.concatenate([matrix(b["vec"]) for b in held]))
            step = max(1, TASK_PAIRS // boxes.low.shape[1])
            for s in range(0, len(q), step):
                some, ids = q[s : s + step], qids[s : s + step]
                far = boxes.bounds(some)
                first = far.argmin(axis=1)
                rows = np.arange(len(some))
                limit = best[s : s + step, -1]
                rows = rows[far[rows, first] <= limit * (1 + 1e-12)]
                first = first[rows]
                keep(s, boxes.within(ids, some, rows, first, limit))
                far[rows, first] = np.inf
                limit = best[s : s + step, -1]
                r, c = np.nonzero((far <= limit[:, None] * (1 + 1e-12)) & np.isfinite(far))
                for t in range(0, len(r), 1 << 14):  # limits sink meanwhile
                    limit = best[s : s + step, -1]
                    a, b = r[t : t + (1 << 14)], c[t : t + (1 << 14)]
                    near = far[a, b] <= limit[a] * (1 + 1e-12)
                    keep(s, boxes.within(ids, some, a[near], b[near], limit))

        held, rows = [], 0
        for b in batches:
            if len(b):
                held.append(b)
                rows += len(b)
            if rows >= BOX_ROWS:
                visit(held)
                held, rows = [], 0
        if held:
            visit(held)
        r, c = np.nonzero(best_id >= 0)
        yield pa.record_batch({"query_id": qids[r], "vec_id": best_id[r, c], "dist": best[r, c]})

    return in_blocks(base.select("vec_id", "vec"), queries, 8 * dim, nearest, NEAR, lambda found: top_k(found, k)).withColumn("dist", F.sqrt("dist"))


def range_search(base: DataFrame, queries: DataFrame, radius: float, self_match: str = "exclude") -> DataFrame:
    """(query_id, vec_id, dist) of all pairs within the radius. Norms bound distances from below, so most pairs are never computed."""
    dim = len((queries.select("vec").first() or [[0]])[0])

    def within(block: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q = block
        qn = np.sqrt((q * q).sum(axis=1))
        order = np.argsort(qn)
        for b in batches:
            if not len(b):
                continue
            ids, x = b["vec_id"].to_numpy(), matrix(b["vec"])
            xn = np.sqrt((x * x).sum(axis=1))
            lo, hi = np.searchsorted(qn[order], [xn - radius - 1e-9, xn + radius + 1e-9])
            for s in range(0, len(ids), 1024):
                at = order[lo[s : s + 1024].min(initial=len(q)) : hi[s : s + 1024].max(initial=0)]
                for t in range(0, len(at), 4096):
                    some, part = at[t : t + 4096], x[s : s + 1024]
                    near = (q[some] * q[some]).sum(1)[:, None] - 2 * (q[some] @ part.T) + (part * part).sum(1)[None, :]
                    r, c = np.nonzero(near <= radius * radius + 1e-9 * (1 + near.max(initial=0)))  # a product picks, folded sums decide
                    acc = np.zeros(len(r))
                    for k in range(q.shape[1]):
                        diff = q[some[r], k] - part[c, k]
                        acc += diff * diff
                    d = np.sqrt(acc)
                    ok = d <= radius
                    if self_match == "exclude":
                        ok &= qids[some[r]] != ids[s + c]
                    yield pa.record_batch({"query_id": qids[some[r]][ok], "vec_id": ids[s + c][ok], "dist": d[ok]})

    return in_blocks(base.select("vec_id", "vec"), queries, 8 * dim, within, NEAR, lambda found: found)


def count_nearer(base: DataFrame, limits: DataFrame) -> DataFrame:
    """(query_id, n): how many rows of the base are nearer to each query (vec_id, vec, far) than its distance `far`, queries without any left out. A matrix
    product decides pairs that are clearly on one side, folded sums the others. The limits travel as one more component of the query vectors."""
    asked = limits.select("vec_id", F.concat("vec", F.array("far")).alias("vec"))
    dim = len((asked.select("vec").first() or [[0]])[0])

    def count(block: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q, far = block[0], np.ascontiguousarray(block[1][:, :-1]), block[1][:, -1]
        n, qq = np.zeros(len(q), np.int64), (q * q).sum(1)
        for b in batches:
            if not len(b):
                continue
            x = matrix(b["vec"])
            xx = (x * x).sum(1)
            step = max(1, TASK_PAIRS // len(b))
            for s in range(0, len(q), step):
                some = slice(s, s + step)
                slack = 1e-9 * (1 + qq[some, None] + xx[None, :] + (far[some] ** 2)[:, None])
                over = qq[some, None] - 2 * (q[some] @ x.T) + xx[None, :] - (far[some] ** 2)[:, None]
                n[some] += (over < -slack).sum(axis=1)
                r, c = np.nonzero(np.abs(over) <= slack)
                acc = np.zeros(len(r))
                for d in range(x.shape[1]):
                    diff = q[s + r, d] - x[c, d]
                    acc += diff * diff
                n[some] += np.bincount(r[np.sqrt(acc) < far[s + r]], minlength=len(n[some]))
        yield pa.record_batch({"query_id": qids[n > 0], "n": n[n > 0]})

    return in_blocks(base.select("vec_id", "vec"), asked, 8 * dim, count, "query_id long, n long", lambda found: found.groupBy("query_id").agg(F.sum("n").alias("n")))


def pair_sums(base: DataFrame, queries: DataFrame, *kinds: str) -> DataFrame:
    """(a, b, na, nb, one column for each of `kinds`) of every query a with every other row b of the base (vec_id, vec, norm): norms as given, `l2_sq` the squared distance, `dot` the inner
    product, `toward` the inner product of a - b with a. Sums fold over the dimensions in order, for a block of pairs at a time."""
    one = lambda rows: rows.select("vec_id", F.concat("vec", F.array("norm")).alias("vec"))
    asked, schema = one(queries), "a long, b long, na double, nb double" + "".join(f", {k} double" for k in kinds)
    dim = len((asked.select("vec").first() or [[0]])[0])

    def sums(block: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q, norm = block[0], np.ascontiguousarray(block[1][:, :-1].T), block[1][:, -1]
        for rows in batches:
            whole = matrix(rows["vec"]) if len(rows) else np.zeros((0, 1))
            step = max(1, PAIR_BLOCK // max(1, len(qids)))
            for s in range(0, len(rows), step):
                ids, x, own = rows["vec_id"].to_numpy()[s : s + step], np.ascontiguousarray(whole[s : s + step, :-1].T), whole[s : s + step, -1]
                acc = {k: np.zeros((len(ids), len(qids))) for k in kinds}
                for y, z in zip(x, q, strict=True):
                    diff = z[None, :] - y[:, None] if {"l2_sq", "toward"} & set(kinds) else None
                    for k in kinds:
                        acc[k] += diff * diff if k == "l2_sq" else diff * z[None, :] if k == "toward" else y[:, None] * z[None, :]
                b, a = np.nonzero(ids[:, None] != qids[None, :])
                yield pa.record_batch({"a": qids[a], "b": ids[b], "na": norm[a], "nb": own[b], **{k: v[b, a] for k, v in acc.items()}})

    return in_blocks(one(base), asked, 8 * dim, sums, schema, lambda found: found)


def filtered_knn(base: DataFrame, queries: DataFrame, where: Column, k: int = 10) -> DataFrame:
    """Nearest rows among those that pass the predicate; it is applied before the scan of vectors, so it is pushed to the files where they hold its columns."""
    return exact_knn(base.where(where), queries, k)


def knn_join(a: DataFrame, b: DataFrame, k: int = 5) -> DataFrame:
    """For every row of a its k nearest rows of b, both sides in blocks."""
    return exact_knn(b, a, k)


def mutual_knn(vectors: DataFrame, k: int = 5) -> DataFrame:
    """(a, b, dist), a < b: pairs each of which is among the k nearest of the other."""
    near = exact_knn(vectors, vectors, k).select("query_id", "vec_id", "dist")
    pairs = near.select(F.least("query_id", "vec_id").alias("a"), F.greatest("query_id", "vec_id").alias("b"), "dist")
    return pairs.groupBy("a", "b").agg(F.count("*").alias("n"), F.max("dist").alias("dist")).where("n = 2").select("a", "b", "dist")


def rerank(candidates: DataFrame, base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Candidates (query_id, vec_id) measured on the original vectors; the k nearest. The base is joined on the candidates' ids only."""
    from ..functions.vectors import l2

    wanted = candidates.select("query_id", "vec_id").distinct()
    joined = wanted.join(base.select("vec_id", F.col("vec").alias("bv")), "vec_id").join(queries.select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qv")), "query_id")
    return top_k(joined.select("query_id", "vec_id", l2("qv", "bv").alias("dist")), k)


def merge_topk(per_segment: DataFrame, k: int) -> DataFrame:
    """Results of all segments (query_id, vec_id, dist, ...) to the k nearest overall."""
    return top_k(per_segment, k)
