"""Graph construction on Spark: levels, segments, candidate lists, neighbour selection, reverse edges, blocks, and whole builds by segment.

A segment is an independent graph of bounded size that one task builds; the number of segments grows with the data. Only what the codec compares with is shuffled to
the segments (codes and tables, not full vectors). The bulk forms (`candidate_lists`, `select_neighbours`, `reverse_edges`) work on plain tables of candidates
without any grouping by segment."""

from __future__ import annotations

import itertools
import math
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .codecs import ExactCodec, matrix
from .exact import exact_knn
from .kernels import Graph, Points, build_bulk, build_layered, reached, select_lists

SEGMENT_ROWS, SEGMENT_BYTES = 1 << 14, 32 << 20  # a task holds several times that beside its lists
ADJACENCY = "segment int, layer int, src long, nbrs array<struct<rank:int,dst:long,dist:double>>"


# -- levels and segments


def level_draw(vec_id: Column, seed: int = 42) -> Column:
    """A number in (0, 1] from an integer hash of the id, the same in every engine."""
    h = (F.pmod(vec_id, F.lit(1 << 31)) * F.lit(2654435761) + F.lit(seed)) % F.lit(1 << 32)
    return (h + 1) / F.lit(float(1 << 32))


def assign_levels(vectors: DataFrame, degree: int = 32, seed: int = 42) -> DataFrame:
    """vectors with `level`: floor(-ln(draw) / ln(degree))."""
    return vectors.withColumn("level", F.floor(-F.log(level_draw(F.col("vec_id"), seed)) / F.lit(math.log(degree))).cast("int"))


def segment_count(n: int, rows: int = SEGMENT_ROWS) -> int:
    return max(1, -(-n // rows))


def default_segments(vectors: DataFrame) -> int:
    """As many segments as keep each below SEGMENT_ROWS rows and its full vectors below SEGMENT_BYTES, with room for uneven hashing."""
    dim = len((vectors.select("vec").first() or [[0]])[0])
    return segment_count(vectors.count(), max(1, min(SEGMENT_ROWS, SEGMENT_BYTES // (8 * max(1, dim)))))


def assign_segments(vectors: DataFrame, segments: int, mode: str = "hash", centres: np.ndarray | None = None) -> DataFrame:
    """vectors with `segment`. hash: by id; range: by order of the id in equal shares (approximate quantiles); coarse: by the nearest of `centres`."""
    if mode == "hash":
        return vectors.withColumn("segment", F.pmod(F.pmod(F.col("vec_id"), F.lit(1 << 31)) * F.lit(2654435761) % F.lit(1 << 32), F.lit(segments)).cast("int"))
    if mode == "range":
        cuts = vectors.approxQuantile("vec_id", [i / segments for i in range(1, segments)], 0.001)
        out = F.lit(0)
        for c in cuts:
            out = out + (F.col("vec_id") > F.lit(c)).cast("int")
        return vectors.withColumn("segment", out.cast("int"))
    sent = vectors.sparkSession.sparkContext.broadcast(centres)

    @F.arrow_udf("int")
    def nearest(v: pa.Array) -> pa.Array:
        x, c = matrix(v), sent.value
        return pa.array(((x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None, :]).argmin(axis=1).astype(np.int32))

    return vectors.withColumn("segment", nearest(F.col("vec")))


# -- bulk forms over tables of candidates


def candidate_lists(base: DataFrame, candidates: int, queries: DataFrame | None = None) -> DataFrame:
    """(src, cands): every vertex with its nearest candidates (id, squared distance), nearest first. The limit case of acquisition with a candidate set that holds all."""
    near = exact_knn(base, queries if queries is not None else base, candidates)
    return near.groupBy(F.col("query_id").alias("src")).agg(F.sort_array(F.collect_list(F.struct("rank", F.col("vec_id").alias("dst"), F.col("dist").alias("dist")))).alias("cands"))


def with_candidate_vectors(cands: DataFrame, base: DataFrame) -> DataFrame:
    """cands with the candidates' vectors in order of rank (cand_vecs), and exact squared distances in place of `dist`."""
    flat = cands.select("src", F.explode("cands").alias("c")).select("src", "c.rank", "c.dst", "c.dist")
    joined = flat.join(base.select(F.col("vec_id").alias("dst"), "vec"), "dst").join(base.select(F.col("vec_id").alias("src"), F.col("vec").alias("own")), "src")
    return joined.groupBy("src").agg(F.first("own").alias("own"), F.sort_array(F.collect_list(F.struct("dist", "dst", "vec"))).alias("c"))


def select_neighbours(lists: DataFrame, degree: int, tau: float = 0.0) -> DataFrame:
    """(src, nbrs): neighbour selection over lists of (dist, dst, vec) in order, `own` the vertex's vector. Many lists advance together in one Arrow batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for s in range(0, len(b), 512):
                part = b.slice(s, 512)
                if not len(part):
                    continue
                c = part["c"]
                offsets = c.offsets.to_numpy()
                flat = c.flatten()
                size = np.diff(offsets)
                vec = matrix(flat.field("vec")) if len(flat) else np.zeros((0, 1))
                own = matrix(part["own"])
                dst = flat.field("dst").to_numpy(zero_copy_only=False)
                width = int(size.max(initial=0))
                ids = np.full((len(part), max(width, 1)), -1, np.int64)
                dist = np.full(ids.shape, np.inf)
                row, place = np.repeat(np.arange(len(part)), size), np.arange(len(flat)) - np.repeat(offsets[:-1] - offsets[0], size)
                acc = np.zeros(len(flat))
                for d in range(vec.shape[1]):  # left to right, as every exact distance
                    diff = own[row, d] - vec[:, d]
                    acc += diff * diff
                ids[row, place], dist[row, place] = np.arange(len(flat)), acc
                kept = select_lists(FoldPoints(vec), ids, dist, degree, tau)
                r, k = np.nonzero(kept >= 0)
                at = kept[r, k]
                nbrs = pa.StructArray.from_arrays([pa.array((k + 1).astype(np.int32)), pa.array(dst[at]), pa.array(np.sqrt(acc[at]))], ["rank", "dst", "dist"])
                cut = np.concatenate([[0], np.cumsum((kept >= 0).sum(axis=1))]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([part["src"], pa.ListArray.from_arrays(pa.array(cut), nbrs)], names=["src", "nbrs"])

    return lists.select("src", "own", "c").mapInArrow(run, "src long, nbrs array<struct<rank:int,dst:long,dist:double>>")


class FoldPoints(Points):
    """Points whose sums fold from left to right."""

    def _sum(self, diff: np.ndarray) -> np.ndarray:
        out = np.zeros(diff.shape[:-1])
        for d in range(diff.shape[-1]):
            out += diff[..., d] * diff[..., d]
        return out


def edges_of(adjacency: DataFrame) -> DataFrame:
    """(src, rank, dst, dist)."""
    return adjacency.select("src", F.explode("nbrs").alias("e")).select("src", "e.rank", "e.dst", "e.dist")


def reverse_edges(adjacency: DataFrame, base: DataFrame, degree: int, tau: float = 0.0) -> DataFrame:
    """(src, nbrs): each list joined with the vertices that chose it; lists that overflow are selected anew, the others keep all in order of distance."""
    e = edges_of(adjacency).select("src", "dst", "dist")
    both = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")).groupBy("src", "dst").agg(F.min("dist").alias("dist"))
    joined = both.join(base.select(F.col("vec_id").alias("dst"), "vec"), "dst").join(base.select(F.col("vec_id").alias("src"), F.col("vec").alias("own")), "src")
    lists = joined.groupBy("src").agg(F.first("own").alias("own"), F.sort_array(F.collect_list(F.struct("dist", "dst", "vec"))).alias("c"))
    whole = lists.where(F.size("c") <= degree).select("src", F.transform("c", lambda x, i: F.struct((i + 1).cast("int").alias("rank"), x["dst"].alias("dst"), x["dist"].alias("dist"))).alias("nbrs"))
    return whole.unionByName(select_neighbours(lists.where(F.size("c") > degree), degree, tau))


def bulk_graph(base: DataFrame, candidates: int, degree: int, tau: float = 0.0) -> DataFrame:
    """(src, nbrs): candidates, selection, reverse edges, selection, as whole-table steps."""
    lists = with_candidate_vectors(candidate_lists(base, candidates), base)
    return reverse_edges(select_neighbours(lists, degree, tau), base, degree, tau)


def check_graph(edges: DataFrame, degree: int) -> DataFrame:
    """One row of violations of edges (src, dst): lists over the degree, loops, repeated edges, edges to nowhere."""
    per = edges.groupBy("src").agg(F.count("*").alias("n"), F.count_distinct("dst").alias("d"), F.sum((F.col("src") == F.col("dst")).cast("long")).alias("loops"))
    sums = per.agg(F.sum((F.col("n") > degree).cast("long")).alias("over_degree"), F.sum("loops").alias("loops"), F.sum(F.col("n") - F.col("d")).alias("repeated"), F.count("*").alias("vertices"), F.sum("n").alias("edges"))
    nowhere = edges.select(F.col("dst").alias("v")).distinct().join(edges.select(F.col("src").alias("v")).distinct(), "v", "left_anti").agg(F.count("*").alias("without_list"))
    return sums.join(nowhere, how="cross")  # one row each


def reachable(edges: DataFrame, entry: int, rounds: int | None = None) -> DataFrame:
    """(v, hop): vertices reached from the entry, by joins of the frontier with the edges; every few rounds the state is written to the shared folder. With `rounds`,
    vertices that are farther raise an error."""
    from ..sources.tables import stored

    spark = edges.sparkSession
    seen = spark.createDataFrame([(entry, 0)], "v long, hop int")
    front, hop = seen, 0
    while True:
        hop += 1
        step = edges.join(front.select(F.col("v").alias("src")), "src").select(F.col("dst").alias("v")).distinct().join(seen.select("v"), "v", "left_anti").withColumn("hop", F.lit(hop))
        front = stored(step, "frontier")
        if front.isEmpty():
            break
        if rounds is not None and hop > rounds:
            raise RuntimeError(f"there are vertices beyond {rounds} hops")
        seen = seen.unionByName(front)
        if hop % 8 == 0:
            seen = stored(seen, "reached")
    return seen


def frontier_search(edges: DataFrame, base: DataFrame, queries: DataFrame, entry: int, width: int, max_iter: int | None = None) -> DataFrame:
    """(query_id, vec_id, dist): best-first search of all queries together as a loop of joins; each round expands every query's nearest unexpanded candidate. One join with
    the adjacency and one with the vectors a round; state is a table in the shared folder. It ends when no query has an unexpanded candidate among its nearest `width`;
    a walk that still has one after `max_iter` rounds is an error, never a shorter result."""
    from ..functions.vectors import l2_sq
    from ..sources.tables import stored

    q = queries.select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qv"))
    points = base.select("vec_id", "vec")
    measure = lambda pairs: pairs.join(q, "query_id").join(points, "vec_id").select("query_id", "vec_id", l2_sq("qv", "vec").alias("dist"))
    state = stored(measure(q.select("query_id", F.lit(entry).cast("long").alias("vec_id"))).withColumn("done", F.lit(False)), "walk")
    w = W.partitionBy("query_id").orderBy("dist", "vec_id")
    for rounds in itertools.count(1):
        held = state.withColumn("r", F.row_number().over(w)).where(F.col("r") <= width)
        pick = held.where(~F.col("done")).groupBy("query_id").agg(F.min(F.struct("dist", "vec_id")).alias("x")).select("query_id", F.col("x.vec_id").alias("src"))
        fresh = pick.join(edges.select("src", F.col("dst").alias("vec_id")), "src").select("query_id", "vec_id").join(state.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_anti")
        done = state.join(pick.select("query_id", F.col("src").alias("vec_id"), F.lit(True).alias("now")), ["query_id", "vec_id"], "left").select("query_id", "vec_id", "dist", (F.col("done") | F.coalesce("now", F.lit(False))).alias("done"))
        state = stored(done.unionByName(measure(fresh).withColumn("done", F.lit(False))), "walk")
        if state.withColumn("r", F.row_number().over(w)).where((F.col("r") <= width) & ~F.col("done")).isEmpty():
            break
        if max_iter is not None and rounds >= max_iter:
            raise RuntimeError(f"the walk has open candidates after {max_iter} rounds")
    return state.withColumn("r", F.row_number().over(w)).where(F.col("r") <= width).select("query_id", "vec_id", F.sqrt("dist").alias("dist"))


# -- neighbour blocks


def pack_blocks(edges: DataFrame, codes: DataFrame, block: int = 16) -> DataFrame:
    """(src, block_no, ids, codes): neighbours in blocks of `block`, ids first, then their codes by subspace; short blocks are padded with -1. Codes are joined once, here."""
    joined = edges.select("src", "rank", "dst").join(codes.select(F.col("vec_id").alias("dst"), "code"), "dst")
    number = F.floor((F.col("rank") - 1) / block).cast("int")
    grouped = joined.withColumn("block_no", number).groupBy("src", "block_no").agg(F.sort_array(F.collect_list(F.struct("rank", "dst", "code"))).alias("g"))
    pad = F.lit(block) - F.size("g")
    ids = F.concat(F.transform("g", lambda x: x["dst"]), F.array_repeat(F.lit(-1).cast("long"), pad))
    m = F.size(F.get("g", F.lit(0))["code"])
    by_subspace = F.transform(F.sequence(F.lit(0), m - 1), lambda s: F.concat(F.transform("g", lambda x: F.get(x["code"], s)), F.array_repeat(F.lit(-1), pad)))
    return grouped.select("src", "block_no", ids.alias("ids"), by_subspace.alias("codes"))


def block_distances(blocks: DataFrame, k: int, batched: bool = True) -> DataFrame:
    """blocks with `adt` (M x K, flat) to (src, block_no, query_id, dst, qdist): for every subspace one take of the table for all neighbours of the block; batched=False
    adds neighbour by neighbour."""

    @F.arrow_udf("array<int>")
    def look_up(adt: pa.Array, codes: pa.Array) -> pa.Array:
        if not len(adt):
            return pa.array([], pa.list_(pa.int32()))
        by = codes.flatten().flatten().to_numpy().astype(np.int64).reshape(len(codes), len(codes[0]), -1)
        tables = adt.flatten().to_numpy().astype(np.int64).reshape(len(adt), by.shape[1], k)
        if batched:
            total = np.zeros((len(by), by.shape[2]), np.int64)
            for m in range(by.shape[1]):
                total += np.take_along_axis(tables[:, m], np.maximum(by[:, m], 0), axis=1)
        else:
            total = np.array([[sum(int(table[m, max(code[m, j], 0)]) for m in range(len(code))) for j in range(code.shape[1])] for table, code in zip(tables, by, strict=True)])
        return pa.ListArray.from_arrays(pa.array(np.arange(len(by) + 1, dtype=np.int32) * by.shape[2]), pa.array(total.astype(np.int32).ravel()))

    sums = blocks.withColumn("sums", look_up("adt", "codes"))
    flat = sums.select("query_id", "src", "block_no", F.explode(F.arrays_zip("ids", "sums")).alias("x"))
    return flat.where("x.ids >= 0").select("query_id", "src", "block_no", F.col("x.ids").alias("dst"), F.col("x.sums").cast("long").alias("qdist"))


# -- whole builds


def vector_is_less(codec: ExactCodec) -> bool:
    """Whether a vector is smaller than its table, so that it travels instead: true of product codes of 8 bits."""
    return codec.name == "pq" and codec.m * 4 << codec.bits > 8 * codec.dim


def prepared(vectors: DataFrame, codec: ExactCodec) -> DataFrame:
    """(segment, vec_id, level, own): what goes to the segments. For table codecs the code and the vector's table from one pass (or the vector, if it is
    smaller), else the code."""
    sent = vectors.sparkSession.sparkContext.broadcast(codec)

    @F.arrow_udf("struct<code binary, tables binary>")
    def own(v: pa.Array) -> pa.Array:
        c, x = sent.value, matrix(v)
        if vector_is_less(c):
            return pa.StructArray.from_arrays([pa.array([r.tobytes() for r in c.codes(x).astype(np.int16)], pa.binary()), pa.array([r.tobytes() for r in x], pa.binary())], ["code", "tables"])
        source = c.source(x)
        if isinstance(source, Points):
            return pa.StructArray.from_arrays([pa.array([r.tobytes() for r in source.x], pa.binary()), pa.nulls(len(x), pa.binary())], ["code", "tables"])
        return pa.StructArray.from_arrays([pa.array([r.tobytes() for r in source.codes], pa.binary()), pa.array([r.tobytes() for r in source.tables], pa.binary())], ["code", "tables"])

    return vectors.select("segment", "vec_id", "level", own(F.col("vec")).alias("p")).select("segment", "vec_id", "level", "p.code", "p.tables")


def source_of(codec: ExactCodec, code: list[bytes], tables: list[bytes] | None, n: int | None = None):
    """The distance source of a segment from its shuffled parts."""
    n = len(code) if n is None else n
    like = codec.source(np.zeros((1, codec.dim)))
    if isinstance(like, Points):
        return Points(np.frombuffer(b"".join(code), like.x.dtype).reshape(n, -1), like.weight)
    from .kernels import LazyTables, Tables

    codes = np.frombuffer(b"".join(code), like.codes.dtype).reshape(n, -1)
    if tables and vector_is_less(codec):
        own = LazyTables(codec, np.frombuffer(b"".join(tables)).reshape(n, -1))
        own = own if codec.lazy(n) else own[np.arange(n)]
        return Tables(codes, own, like.between.reshape(like.m, like.k, like.k), like.wide, like.block)
    own = np.frombuffer(b"".join(tables), like.tables.dtype).reshape(n, *like.tables.shape[1:]) if tables else None
    return Tables(codes, own, like.between.reshape(like.m, like.k, like.k), like.wide, like.block)


def rows_of(graph: Graph, ids: np.ndarray, segment: int, levels: np.ndarray) -> pa.Table:
    """Adjacency rows of a built graph; distances are those of its codes."""
    kind = pa.struct([("rank", pa.int32()), ("dst", pa.int64()), ("dist", pa.float64())])
    schema, parts = pa.schema([("segment", pa.int32()), ("layer", pa.int32()), ("src", pa.int64()), ("nbrs", pa.list_(kind))]), []
    for layer, adj in enumerate(graph.adj):
        at = np.flatnonzero(levels >= layer)
        for s in range(0, len(at), 4096):
            a = at[s : s + 4096]
            nb = adj[a].astype(np.int64)
            d = graph.source.pair(a, nb).astype(np.float64)
            row, col = np.nonzero(nb >= 0)
            rank = np.arange(len(row)) - np.searchsorted(row, row) + 1
            flat = pa.StructArray.from_arrays([pa.array(rank.astype(np.int32)), pa.array(ids[nb[row, col]]), pa.array(d[row, col])], fields=list(kind))
            cut = pa.array(np.searchsorted(row, np.arange(len(a) + 1)).astype(np.int32))
            fill = lambda x: pa.array(np.full(len(a), x, np.int32))
            parts.append(pa.table([fill(segment), fill(layer), pa.array(ids[a]), pa.ListArray.from_arrays(cut, flat)], schema=schema))
    return pa.concat_tables(parts) if parts else schema.empty_table()


def construct(codec: ExactCodec, source, levels: np.ndarray, candidates: int, degree: int, strategy: str, base_factor: int, tau: float, batch: int) -> Graph:
    inline = bool(getattr(codec, "inline", False))
    if strategy == "bulk":
        return build_bulk(source, candidates, degree, tau, inline=inline)
    if strategy == "spanning":
        return build_spanning(source, candidates, degree, tau, inline)
    return build_layered(source, levels, candidates, degree, base_factor, 1 if strategy == "sequential" else batch, inline, tau)


def build_spanning(source, candidates: int, degree: int, tau: float, inline: bool) -> Graph:
    """Single layer around a navigating vertex: candidates are the nearest vertices and those met on the way from the navigating vertex; what stays unreached is attached."""
    from .kernels import beam, ensure_reachable, link_back, without_mutual

    graph = build_bulk(source, candidates, degree, tau, reachable=False, inline=inline)
    n = source.n
    lists = []
    for s in range(0, n, 256):
        at = np.arange(s, min(n, s + 256))
        ids, dist = beam(graph, 0, source.own(at), np.full(len(at), graph.entry), candidates)
        mine = graph.adj[0][at].astype(np.int64)
        md = source.pair(at, mine).astype(np.float64)
        md[mine < 0] = np.inf
        dup = (ids[:, None, :] == mine[:, :, None]).any(axis=2)
        md[dup] = np.inf
        dist = np.where((ids == at[:, None]) | (ids < 0), np.inf, dist)
        c, d = np.concatenate([ids, mine], 1), np.concatenate([dist, md], 1)
        order = np.argsort(d, axis=1, kind="stable")
        c, d = np.take_along_axis(c, order, 1), np.take_along_axis(d, order, 1)
        lists.append(select_lists(source, np.where(np.isfinite(d), c, -1), d, degree, tau, graph.count))
    fresh = np.concatenate(lists) if lists else np.zeros((0, degree), np.int64)
    graph.set(0, np.arange(n), fresh)
    link_back(graph, 0, np.arange(n), without_mutual(graph, 0, np.arange(n), fresh), tau)
    ensure_reachable(graph)
    return graph


REPORT = "segment int, n long, metric string, value double"


def build_graph(vectors: DataFrame, codec: ExactCodec, candidates: int = 128, degree: int = 16, strategy: str = "batched", segments: int | None = None, base_factor: int = 2, tau: float = 0.0, batch: int = 256, report: bool = False) -> DataFrame:
    """Adjacency (segment, layer, src, nbrs) of a graph for each segment, or with report=True its counters and seconds (segment, n, metric, value). The codec must be fitted."""
    placed = assign_segments(vectors.select("vec_id", "vec"), segments or default_segments(vectors))
    return build_segments(placed, codec, candidates, degree, strategy, base_factor, tau, batch, report)


def build_segments(placed: DataFrame, codec: ExactCodec, candidates: int = 128, degree: int = 16, strategy: str = "batched", base_factor: int = 2, tau: float = 0.0, batch: int = 256, report: bool = False) -> DataFrame:
    """The same for vectors that have their segment."""
    placed = assign_levels(placed.select("vec_id", "vec", "segment"), degree)
    parts = prepared(placed if strategy not in ("bulk", "spanning") else placed.withColumn("level", F.lit(0)), codec)
    sent = placed.sparkSession.sparkContext.broadcast(codec)

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("vec_id").combine_chunks()
        c, began = sent.value, time.perf_counter()
        tables = None if rows["tables"].null_count else [x.as_buffer() for x in rows["tables"]]
        source = source_of(c, [x.as_buffer() for x in rows["code"]], tables)
        ids, levels, segment = rows["vec_id"].to_numpy(), rows["level"].to_numpy().astype(np.int64), rows["segment"][0].as_py()
        graph = construct(c, source, levels, min(candidates, max(1, len(rows) - 1)), degree, strategy, base_factor, tau, batch)
        took = time.perf_counter() - began
        if report:
            count = dict(graph.count) | {"build_seconds": took, "edges": float(sum(int((a >= 0).sum()) for a in graph.adj)), "reached": float(reached(graph).sum()), "entry": float(ids[graph.entry])}
            return pa.table({"segment": pa.array([segment] * len(count), pa.int32()), "n": pa.array([len(rows)] * len(count), pa.int64()), "metric": list(count), "value": pa.array(list(map(float, count.values())), pa.float64())})
        return rows_of(graph, ids, segment, levels)

    return parts.groupBy("segment").applyInArrow(run, REPORT if report else ADJACENCY)
