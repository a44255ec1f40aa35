"""Search of built graphs: every query visits every segment, local results merge, the best few are measured again on full vectors."""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .codecs import ExactCodec, matrix
from .exact import exact_knn, in_blocks, merge_topk, rerank, top_k
from .graph import assign_levels, assign_segments, build_graph, build_segments, default_segments, prepared, source_of
from .kernels import Graph, Points, descend, early_abort, reached

FOUND = "query_id long, segment int, vec_id long, dist double, hops double, distances double"
PACKED = "segment int, ids binary, code binary, vecs binary, layers array<struct<at: binary, lists: binary>>"


class Index:
    """A fitted codec, the vectors with their segment, and the adjacency, as DataFrames that can be stored. `gone` holds deleted ids until a rebuild."""

    def __init__(self, vectors: DataFrame, codec: ExactCodec, adjacency: DataFrame, segments: int, degree: int, how: dict | None = None, gone: DataFrame | None = None):
        self.vectors, self.codec, self.adjacency, self.segments, self.degree = vectors, codec, adjacency, segments, degree
        self.how, self.gone = how or {}, gone
        self._packed: dict[bool, DataFrame] = {}

    def placed(self) -> DataFrame:
        """(vec_id, vec, segment): ingested vectors carry their segment, others get it from their id."""
        if "segment" in self.vectors.columns:
            return self.vectors.select("vec_id", "vec", "segment")
        return assign_segments(self.vectors.select("vec_id", "vec"), self.segments)

    def packed(self, full: bool = False) -> DataFrame:
        """One row for each segment: ids, codes (with `full` the vectors too) and neighbour lists as arrays of bytes. Written once, on first use; a walk reads
        it without any shuffle."""
        from ..sources.tables import stored

        if full not in self._packed:
            parts = prepared(assign_levels(self.placed(), self.degree), self.codec).select("segment", "vec_id", "code")
            if full:
                parts = parts.join(self.vectors.select("vec_id", "vec"), "vec_id")
            lists = self.adjacency.select("segment", "layer", "src", F.transform("nbrs", lambda x: x["dst"]).alias("nbrs"))
            self._packed[full] = stored(parts.groupBy("segment").cogroup(lists.groupBy("segment")).applyInArrow(pack_segment, PACKED), "packed-segments")
        return self._packed[full]

    def delete(self, ids: DataFrame) -> Index:
        """The same graph without the rows of `ids` (vec_id) in any result: walks still pass through them, as the lists stay as they are, until `rebuilt`."""
        gone = ids.select("vec_id").distinct()
        out = Index(self.vectors, self.codec, self.adjacency, self.segments, self.degree, self.how, gone if self.gone is None else self.gone.unionByName(gone).distinct())
        out._packed = self._packed
        return out

    def live(self) -> DataFrame:
        return self.vectors if self.gone is None else self.vectors.join(self.gone, "vec_id", "left_anti")

    def rebuilt(self, refit: bool = False) -> Index:
        """Segments that lost vertices are built anew from what is left of them; the others keep their lists. refit: train the codec again and build all."""
        if refit or self.gone is None:
            return build_index(self.live().drop("segment"), self.codec, segments=None if refit else self.segments, degree=self.degree, refit=refit, **self.how)
        from ..sources.tables import stored

        placed = stored(self.placed().join(self.gone, "vec_id", "left_anti"), "live-vectors")
        hit = self.placed().join(self.gone, "vec_id", "left_semi").select("segment").distinct()
        fresh = build_segments(placed.join(F.broadcast(hit), "segment", "left_semi"), self.codec, degree=self.degree, **self.how)
        adjacency = stored(self.adjacency.join(F.broadcast(hit), "segment", "left_anti").unionByName(fresh), "adjacency")
        return Index(self.live(), self.codec, adjacency, self.segments, self.degree, self.how)


def build_index(vectors: DataFrame, codec: ExactCodec, candidates: int = 128, degree: int = 16, segments: int | None = None, refit: bool = True, **how) -> Index:
    """Without `segments`, as many as bound the rows and bytes of each (`default_segments`)."""
    from ..sources.tables import stored

    if refit:
        codec.fit(vectors)
    segments = segments or default_segments(vectors)
    adjacency = stored(build_graph(vectors, codec, candidates, degree, segments=segments, **how), "adjacency")
    return Index(vectors, codec, adjacency, segments, degree, {"candidates": candidates} | how)


def pack_segment(parts: pa.Table, lists: pa.Table) -> pa.Table:
    schema = pa.schema([("segment", pa.int32()), ("ids", pa.binary()), ("code", pa.binary()), ("vecs", pa.binary()), ("layers", pa.list_(pa.struct([("at", pa.binary()), ("lists", pa.binary())])))])
    if not len(parts):
        return schema.empty_table()
    parts = parts.sort_by("vec_id").combine_chunks()
    ids = parts["vec_id"].to_numpy()
    layer, src, nbrs = lists["layer"].to_numpy(), lists["src"].to_numpy(), lists.combine_chunks()["nbrs"].combine_chunks()
    nbrs = nbrs if isinstance(nbrs, pa.Array) else pa.array([], pa.list_(pa.int64()))
    size = nbrs.value_lengths().to_numpy(zero_copy_only=False) if len(nbrs) else np.zeros(0, np.int64)
    flat = np.searchsorted(ids, nbrs.flatten().to_numpy()).astype(np.int32) if len(nbrs) else np.zeros(0, np.int32)
    row = np.repeat(np.arange(len(nbrs)), size)
    place = np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)
    layers = []
    for k in range(int(layer.max(initial=0)) + 1):
        some = np.flatnonzero(layer == k)
        out = np.full((len(some), max(1, int(size[some].max(initial=0)))), -1, np.int32)
        here = layer[row] == k
        out[np.searchsorted(some, row[here]), place[here]] = flat[here]
        layers.append({"at": np.searchsorted(ids, src[some]).astype(np.int32).tobytes(), "lists": out.tobytes()})
    vecs = matrix(parts["vec"]).tobytes() if "vec" in parts.column_names else None
    return pa.Table.from_pylist([{"segment": parts["segment"][0].as_py(), "ids": ids.tobytes(), "code": b"".join(x.as_buffer() for x in parts["code"]), "vecs": vecs, "layers": layers}], schema)


def load_segment(c: ExactCodec, row: dict, full: bool, turn: np.ndarray | None = None) -> tuple[Graph, np.ndarray]:
    """The graph of one packed segment; with full=True distances are those of the full vectors (rotated by `turn`)."""
    ids = np.frombuffer(row["ids"], np.int64)
    if full:
        x = np.frombuffer(row["vecs"]).reshape(len(ids), -1)
        source = Points(x if turn is None else x @ turn)
    else:
        source = source_of(c, [row["code"]], None, len(ids))
    at = [np.frombuffer(k["at"], np.int32) for k in row["layers"]]
    lists = [np.frombuffer(k["lists"], np.int32).reshape(len(a), -1) if len(a) else np.zeros((0, 1), np.int32) for a, k in zip(at, row["layers"], strict=True)]
    graph = Graph(len(ids), [x.shape[1] for x in lists], source, bool(getattr(c, "inline", False)) and not full)
    for k, (a, x) in enumerate(zip(at, lists, strict=True)):
        graph.set(k, a, x)
        if len(a):
            graph.top, graph.entry = k, int(a.min())
    return graph, ids


def reach(index: Index, full: bool = False) -> DataFrame:
    """(segment, n, reached): the vertices of each segment, and those that the lists of its lowest layer reach from the entry."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(len(batch)):
                row = batch.slice(at, 1).to_pylist()[0]
                seen = reached(load_segment(codec.value, row, full)[0])
                yield pa.record_batch({"segment": pa.array([row["segment"]], pa.int32()), "n": [len(seen)], "reached": [int(seen.sum())]})

    codec = index.vectors.sparkSession.sparkContext.broadcast(index.codec)
    return index.packed(full).mapInArrow(run, "segment int, n long, reached long")


def search(index: Index, queries: DataFrame, k: int = 10, ef: int = 64, mode: str = "codes", distance: str = "full", eps: float = 2.1, chunk: int = 16, stop: str = "exhaust", window: int = 16, r: int | None = None, where: Column | None = None, policy: str = "auto") -> DataFrame:
    """(query_id, rank, vec_id, dist). mode: codes (distances of the codes), codes+rerank, exact (full vectors on the graph that codes built).
    distance='early_abort' adds dimensions of randomly rotated vectors until a candidate is out; stop='relaxed' ends a walk when the last distances stay above the result.
    where: only rows that pass; 'pre' scans them exactly, 'post' over-fetches and filters, 'auto' decides by the share that passes."""
    if where is not None:
        return filtered_search(index, queries, where, policy, k, ef, mode)
    found = walk(index, queries, ef, mode, distance, eps, chunk, stop, window)
    local = found.select("query_id", "vec_id", "dist")
    if mode == "codes+rerank":
        return rerank(top_k(local, r or ef), index.vectors, queries, k)
    return merge_topk(local, k)


def walk(index: Index, queries: DataFrame, ef: int, mode: str = "codes", distance: str = "full", eps: float = 2.1, chunk: int = 16, stop: str = "exhaust", window: int = 16) -> DataFrame:
    """(query_id, segment, vec_id, dist, hops, distances): the candidate set of every query in every segment, with its share of the counters."""
    full = mode == "exact" or distance == "early_abort"
    sent = queries.sparkSession.sparkContext.broadcast(index.codec)

    def run(block: tuple, batches) -> Iterator[pa.RecordBatch]:
        c, (qids, q) = sent.value, block
        turn = np.linalg.qr(np.random.default_rng(5).normal(size=(q.shape[1],) * 2))[0] if distance == "early_abort" else None
        for batch in batches:
            for at in range(len(batch)):
                row = batch.slice(at, 1).to_pylist()[0]
                graph, ids = load_segment(c, row, full, turn)
                for s in range(0, len(q), 256):
                    part = q[s : s + 256] if turn is None else q[s : s + 256] @ turn
                    graph.count = Counter()
                    how = {"window": window if stop == "relaxed" else 0}
                    if turn is not None:
                        how["measure"] = early_abort(graph.source.x, part, chunk, eps, graph.count)
                    found, dist = descend(graph, part if full else c.query_state(part), ef, **how)
                    r, col = np.nonzero(found >= 0)
                    d = dist[r, col].astype(np.float64)
                    d = np.sqrt(d) if full or c.name in ("exact", "sq", "pca", "pq") else d
                    work = graph.count["dimensions"] / graph.source.x.shape[1] if turn is not None else graph.count["distances"]
                    yield pa.record_batch({"query_id": qids[s : s + 256][r], "segment": pa.array(np.full(len(r), row["segment"], np.int32)), "vec_id": ids[found[r, col]], "dist": d, "hops": np.full(len(r), graph.count["hops"] / len(part)), "distances": np.full(len(r), work / len(part))})

    dim = len((queries.select("vec").first() or [[0]])[0])
    found = in_blocks(index.packed(full), queries, 8 * dim, run, FOUND, lambda x: x)
    return found if index.gone is None else found.join(index.gone, "vec_id", "left_anti").select("query_id", "segment", "vec_id", "dist", "hops", "distances")


def filtered_search(index: Index, queries: DataFrame, where: Column, policy: str = "auto", k: int = 10, ef: int = 64, mode: str = "codes+rerank") -> DataFrame:
    """Nearest rows that pass the predicate over the index's vectors."""
    rows = index.live()
    share = rows.agg(F.avg(where.cast("double"))).first()[0] or 0.0
    if policy == "pre" or (policy == "auto" and share < 0.2):
        return exact_knn(rows.where(where), queries, k)
    from ..sources.tables import stored

    # a walk that brings fewer than k passing rows is repeated twice as wide, until it has k or all that it can reach
    wide, want = max(ef, int(ef / max(share, 1e-9))), min(k, rows.where(where).count())
    largest = index.placed().groupBy("segment").count().agg(F.max("count")).first()[0] or 0
    while True:
        found = stored(walk(index, queries, min(wide, largest), mode), "walk").select("query_id", "vec_id", "dist")
        passing = found.join(rows.where(where).select("vec_id"), "vec_id", "left_semi")
        short = queries.select(F.col("vec_id").alias("query_id")).join(passing.groupBy("query_id").agg(F.count("*").alias("n")), "query_id", "left").where(F.coalesce("n", F.lit(0)) < want)
        if wide >= largest or short.isEmpty():
            break
        wide *= 2
    if not short.isEmpty():  # vertices that a walk cannot reach: those queries are answered by the scan
        exact = exact_knn(rows.where(where), queries.join(short.select(F.col("query_id").alias("vec_id")), "vec_id", "left_semi"), k)
        passing = passing.join(short, "query_id", "left_anti").unionByName(exact.select("query_id", "vec_id", "dist"))
    return rerank(top_k(passing, max(ef, k)), index.vectors, queries, k) if mode == "codes+rerank" else top_k(passing, k)


def code_scan(vectors: DataFrame, codec: ExactCodec, queries: DataFrame, k: int = 10) -> DataFrame:
    """(query_id, rank, vec_id, dist): nearest rows by the codes alone, without a graph; every task scans its codes for all queries of a broadcast block."""
    sent = vectors.sparkSession.sparkContext.broadcast(codec)

    def scan(block: tuple, batches) -> Iterator[pa.RecordBatch]:
        c, (ids_q, q) = sent.value, block
        state = c.query_state(q)
        for b in batches:
            if not len(b):
                continue
            ids, source = b["vec_id"].to_numpy(), c.source(matrix(b["vec"]))
            d = np.concatenate([source.of(state[s : s + 64], np.tile(np.arange(len(ids)), (len(state[s : s + 64]), 1))).astype(np.float64) for s in range(0, len(q), 64)])
            d[ids_q[:, None] == ids[None, :]] = np.inf
            kk = min(k, len(ids))
            # all that can be among the k best, ties included
            bound = np.partition(d, kk - 1, axis=1)[:, kk - 1]
            r, col = np.nonzero((d <= bound[:, None]) & np.isfinite(d))
            yield pa.record_batch({"query_id": ids_q[r], "vec_id": ids[col], "dist": d[r, col]})

    return in_blocks(vectors.select("vec_id", "vec"), queries, 2048, scan, "query_id long, vec_id long, dist double", lambda found: top_k(found, k))


def coarse_cells(vectors: DataFrame, cells: int, iters: int = 4) -> np.ndarray:
    """Centres of coarse cells by Lloyd's algorithm on the whole vector as one subspace."""
    from .codecs import train_codebooks

    dim = len(vectors.select("vec").first()[0])
    return train_codebooks(vectors.select("vec_id", "vec"), [(0, dim)], cells, iters)[0]


def ivf_scan(vectors: DataFrame, codec: ExactCodec, centres: np.ndarray, queries: DataFrame, nprobe: int = 4, k: int = 10, r: int = 100) -> DataFrame:
    """Inverted-file scan: rows and queries meet by cell (a query in its nprobe nearest cells), codes are scanned within, the r best are measured again. Cells are
    split by salt, so a crowded cell is shared among tasks."""
    rows = assign_segments(vectors.select("vec_id", "vec"), len(centres), "coarse", centres).withColumnRenamed("segment", "cell")
    size = rows.groupBy("cell").agg(F.count("*").alias("n")).select("cell", F.greatest(F.ceil(F.col("n") / 100_000), F.lit(1)).cast("int").alias("salts"))
    rows = rows.join(F.broadcast(size), "cell").withColumn("salt", F.pmod(F.xxhash64("vec_id"), F.col("salts")).cast("int"))
    spark = vectors.sparkSession
    sent_c = spark.sparkContext.broadcast(centres)

    @F.arrow_udf("array<int>")
    def probes(v: pa.Array) -> pa.Array:
        x, c = matrix(v), sent_c.value
        d = (x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None, :]
        best = np.argsort(d, axis=1, kind="stable")[:, : min(nprobe, len(c))].astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(np.arange(len(best) + 1, dtype=np.int32) * best.shape[1]), pa.array(best.reshape(-1)))

    asked = queries.select(F.col("vec_id").alias("query_id"), F.col("vec").alias("q")).withColumn("ask_cell", F.explode(probes("q"))).join(F.broadcast(size.withColumnRenamed("cell", "ask_cell")), "ask_cell").withColumn("ask_salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)))
    sent = spark.sparkContext.broadcast(codec)

    def run(key: tuple, own: pd.DataFrame, asks: pd.DataFrame) -> pd.DataFrame:
        if not len(own) or not len(asks):
            return pd.DataFrame(columns=["query_id", "vec_id", "dist"])
        c = sent.value
        source = c.source(np.stack(own["vec"].to_numpy()).astype(np.float64))
        ids, qids = own["vec_id"].to_numpy(), asks["query_id"].to_numpy()
        state = c.query_state(np.stack(asks["q"].to_numpy()).astype(np.float64))
        out = []
        for s in range(0, len(state), 64):
            d = source.of(state[s : s + 64], np.tile(np.arange(len(ids)), (len(state[s : s + 64]), 1))).astype(np.float64)
            d[qids[s : s + 64, None] == ids[None, :]] = np.inf
            best = np.argsort(d, axis=1, kind="stable")[:, :r]
            row, col = np.nonzero(np.isfinite(np.take_along_axis(d, best, 1)))
            out.append(pd.DataFrame({"query_id": qids[s : s + 64][row], "vec_id": ids[best[row, col]], "dist": d[row, best[row, col]]}))
        return pd.concat(out)

    near = rows.select("cell", "salt", "vec_id", "vec").groupBy("cell", "salt").cogroup(asked.select("ask_cell", "ask_salt", "query_id", "q").groupBy("ask_cell", "ask_salt")).applyInPandas(run, "query_id long, vec_id long, dist double")
    return rerank(top_k(near, r), vectors, queries, k)


def timed_walk(index: Index, queries: DataFrame, ef: int, mode: str = "codes", **how) -> tuple[float, DataFrame]:
    """Seconds of one walk as a Spark action, and its result written to the shared folder."""
    from ..sources.tables import stored

    began = time.perf_counter()
    got = stored(walk(index, queries, ef, mode, **how), "walk-result")
    return time.perf_counter() - began, got
