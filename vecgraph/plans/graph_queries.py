"""Queries that build and search graphs; their results depend on the order of insertion, so they have no SQL and are checked by recall and invariants."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import codecs as C
from ..operators import exact as E
from ..operators import graph as G
from ..operators import measures as M
from ..operators import search as S
from ..operators.kernels import Graph, Points, beam, link_back, lru_misses, select_lists
from ..queries import emb, neat, query, split
from ..sources.tables import stored
from . import sql

CANDIDATES, DEGREE, EF, K = 64, 16, 64, 10


def codec_named(name: str):
    return {"lg": lambda: C.ExactCodec(), "sq": lambda: C.ScalarCodec(8), "pca": lambda: C.PrincipalCodec(0.9), "pq": lambda: C.ProductCodec(16, 8, 4, sample=0), "acc": lambda: C.AlignedCodec(16, 4, 8, iters=4, sample=0, rule="quantile", rounding="nearest")}[name]()


def index_for(spark, d, name: str, segments: int | None = None, **how):
    base, q = split(spark, d)
    return S.build_index(base.select("vec_id", "vec", "label"), codec_named(name), CANDIDATES, DEGREE, segments, **how), q


def _search(name: str, mode: str):
    def run(spark, d) -> DataFrame:
        index, q = index_for(spark, d, name)
        return neat(S.search(index, q, K, EF, mode))

    run.__name__ = f"graph_search_{name}"
    return run


for _name, _mode in (("lg", "exact"), ("sq", "codes"), ("pca", "codes"), ("pq", "codes+rerank"), ("acc", "codes+rerank")):
    query()(_search(_name, _mode))


@query()
def graph_search_segments(spark, d):
    """Four segments built and searched apart, merged and reranked."""
    index, q = index_for(spark, d, "acc", segments=4)
    return neat(S.search(index, q, K, EF, "codes+rerank"))


@query()
def graph_search_bulk(spark, d):
    index, q = index_for(spark, d, "acc", strategy="bulk")
    return neat(S.search(index, q, K, EF, "codes+rerank"))


@query()
def graph_search_sequential(spark, d):
    index, q = index_for(spark, d, "lg", strategy="sequential")
    return neat(S.search(index, q, K, EF, "exact"))


@query()
def spanning_graph(spark, d):
    """Single layer around a navigating vertex."""
    index, q = index_for(spark, d, "acc", strategy="spanning")
    return neat(S.search(index, q, K, EF, "codes+rerank"))


@query()
def relaxed_graph(spark, d):
    """Single layer whose selection is relaxed by 3 tau."""
    index, q = index_for(spark, d, "lg", strategy="bulk", tau=0.01)
    return neat(S.search(index, q, K, EF, "exact"))


@query()
def early_abort(spark, d):
    """Distances given up after some of the randomly rotated dimensions."""
    index, q = index_for(spark, d, "acc")
    return neat(S.search(index, q, K, EF, "exact", distance="early_abort", eps=2.1, chunk=16))


@query()
def relaxed_stop(spark, d):
    index, q = index_for(spark, d, "acc")
    return neat(S.search(index, q, K, EF, "codes+rerank", stop="relaxed", window=16))


@query()
def filtered_graph_search(spark, d):
    index, q = index_for(spark, d, "acc")
    return neat(S.search(index, q, K, EF, "codes+rerank", where=F.col("label").isin(1, 2, 3, 4), policy="post"))


@query()
def frontier_search(spark, d):
    """The same walk as a loop of joins, with a narrow candidate set, for the queries with ids divisible by 50."""
    v = emb(spark, d)
    q = v.where("vec_id % 50 = 0")
    edges = stored(G.edges_of(G.bulk_graph(v, 24, 8)).select("src", "dst"), "edges")
    return neat(E.top_k(G.frontier_search(edges, v, q, 1, 16), 5))


@query()
def ivf_scan(spark, d):
    base, q = split(spark, d)
    codec = codec_named("acc").fit(base)
    return neat(S.ivf_scan(base, codec, S.coarse_cells(base, 16), q, nprobe=6, k=K))


@query(f"""WITH emb AS ({sql.EMB}), centres AS (SELECT vec_id AS c, vec AS cv FROM emb WHERE vec_id < 16),
near AS (SELECT e.vec_id, e.vec, c, row_number() OVER (PARTITION BY e.vec_id ORDER BY {sql.sq('e.vec', 'cv')}, c) AS r FROM emb e JOIN centres ON true),
met AS (SELECT q.vec_id AS query_id, b.vec_id, sqrt({sql.sq('q.vec', 'b.vec')}) AS dist FROM near q JOIN near b ON q.c = b.c AND q.vec_id % 10 = 0 AND q.r <= 6 AND b.vec_id % 10 <> 0 AND b.r = 1),
ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS INTEGER) AS rank FROM met)
SELECT query_id, rank, vec_id, round(dist, 6) + 0.0 AS dist FROM ranked WHERE rank <= 10""")
def ivf_given_cells(spark, d):
    """The inverted file with full vectors in given cells, those of the sixteen least ids: the part of it that SQL can follow."""
    base, q = split(spark, d)
    centres = np.stack([np.array(r["vec"]) for r in emb(spark, d).where("vec_id < 16").orderBy("vec_id").collect()])
    return neat(S.ivf_scan(base, C.ExactCodec().fit(base), centres, q, nprobe=6, k=K))


@query()
def code_scan_recall(spark, d):
    """Recall of the best 100 of a scan by codes alone, for each codec: the quality of the codec apart from the graph."""
    base, q = split(spark, d)
    truth, out = stored(E.exact_knn(base, q, K), "truth"), None
    for name in ("sq", "pca", "pq", "acc"):
        got = S.code_scan(base, codec_named(name).fit(base), q, 100).select("query_id", "vec_id", F.lit(1).alias("hit"))
        one = truth.join(got, ["query_id", "vec_id"], "left").agg((F.count("hit") / F.count("*")).alias("recall_100")).select(F.lit(name).alias("method"), "recall_100")
        out = one if out is None else out.unionByName(one)
    return out


@query()
def cost_counters(spark, d):
    """Counters of a build: distances in acquisition, selection and reverse edges, fetches with and without codes beside the ids, hops."""
    v, out = emb(spark, d), None
    for name in ("lg", "pq", "acc"):
        codec = codec_named(name).fit(v)
        one = G.build_graph(v, codec, CANDIDATES, DEGREE, report=True).where("metric not like '%seconds'").select(F.lit(name).alias("method"), "n", "metric", "value")
        out = one if out is None else out.unionByName(one)
    return out


def traces(x: np.ndarray, codec, queries: np.ndarray, degree: int) -> list[tuple[str, int, int]]:
    """(layout, misses, accesses) of the byte addresses that searches touch, without and with codes beside the ids, on a model of a first-level cache."""
    source = codec.source(x)
    codec.inline = False
    graph = G.construct(codec, source, np.zeros(len(x), np.int64), CANDIDATES, degree, "bulk", 1, 0.0, 256)
    state, out, m = codec.query_state(queries), [], source.m
    visited: list[tuple[int, np.ndarray]] = []

    class Recorder:
        n = source.n

        @staticmethod
        def of(s, ids):
            return source.of(s, ids)

    kept = graph.near

    def near(layer, at, s, rows, ids, fresh):
        visited.extend(zip(at.tolist(), ids, strict=True))
        return kept(layer, at, s, rows, ids, fresh)

    graph.near = near
    for i in range(len(queries)):
        beam(graph, 0, state[i : i + 1], np.array([graph.entry]), 32)
    n, tables = len(x), 1 << 14
    line = lambda start, size: np.arange(start, start + size, 16)
    for layout in ("apart", "inlined"):
        parts = []
        for v, ids in visited:
            parts.append(line(0, m * 16))  # the vector's own table
            if layout == "apart":
                parts.append(line(tables + v * degree * 4, degree * 4))
                parts += [line(tables + n * degree * 4 + int(y) * (64 + m), m) for y in ids[ids >= 0]]
            else:
                parts.append(line(tables + v * degree * (4 + m), degree * (4 + m)))
        misses, total = lru_misses(np.concatenate(parts))
        out.append((layout, misses, total))
    return out


@query()
def cache_model(spark, d):
    base, q = split(spark, d)
    codec = codec_named("acc").fit(base)
    sent = spark.sparkContext.broadcast((codec, np.stack([np.array(r[0]) for r in q.where("vec_id % 50 = 0").orderBy("vec_id").select("vec").collect()])))

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        codec, asks = sent.value
        found = traces(np.stack(rows.sort_values("vec_id")["vec"].to_numpy()).astype(np.float64), codec, asks, DEGREE)
        return pd.DataFrame([(a, b, c, b / max(1, c)) for a, b, c in found], columns=["layout", "misses", "accesses", "miss_rate"])

    return G.assign_segments(base.select("vec_id", "vec"), G.segment_count(base.count(), 10_000)).groupBy("segment").applyInPandas(run, "layout string, misses long, accesses long, miss_rate double").groupBy("layout").agg(F.sum("misses").alias("misses"), F.sum("accesses").alias("accesses")).withColumn("miss_rate", F.col("misses") / F.col("accesses"))


def cycles(x: np.ndarray, queries: np.ndarray, rounds: int, share: float, degree: int, k: int = 10, ef: int = 64) -> list[tuple[int, str, float]]:
    """(cycle, kind, recall): each cycle deletes the oldest share of the live vertices (edges to them go, lists stay unrepaired) and inserts as many new ones; next
    to it the recall of an index built anew from the live vertices."""
    n = len(x)
    start = n // 2
    step = max(1, int(start * share))
    source = Points(x)
    graph = Graph(n, [degree], source)
    live = np.zeros(n, bool)

    def insert(at: np.ndarray) -> None:
        for y in at.tolist():
            if not live.any():
                graph.entry, graph.top = y, 0
                live[y] = True
                continue
            ids, dist = beam(graph, 0, source.own(np.array([y])), np.array([graph.entry]), CANDIDATES)
            ids = np.where((ids >= 0) & live[np.maximum(ids, 0)] & (ids != y), ids, -1)
            dist = np.where(ids >= 0, dist, np.inf)
            order = np.argsort(dist, axis=1, kind="stable")
            lists = select_lists(source, np.take_along_axis(ids, order, 1), np.take_along_axis(dist, order, 1), degree)
            graph.set(0, np.array([y]), lists)
            live[y] = True
            link_back(graph, 0, np.array([y]), lists)

    def recall(g: Graph, alive: np.ndarray) -> float:
        ids = np.flatnonzero(alive)
        truth = ids[np.argsort(((queries[:, None, :] - x[ids][None]) ** 2).sum(-1), axis=1)[:, :k]]
        found, dist = beam(g, 0, queries, np.full(len(queries), g.entry), ef)
        dist = np.where((found >= 0) & alive[np.maximum(found, 0)], dist, np.inf)
        best = np.take_along_axis(found, np.argsort(dist, axis=1)[:, :k], 1)
        return float(np.mean([len(set(t) & set(b)) / k for t, b in zip(truth.tolist(), best.tolist(), strict=True)]))

    insert(np.arange(start))
    out = [(0, "updated", recall(graph, live))]
    next_in, next_out = start, 0
    for c in range(1, rounds + 1):
        gone = np.arange(next_out, min(next_out + step, n))
        next_out += step
        live[gone] = False
        for a in graph.adj:
            dead = (a >= 0) & ~live[np.maximum(a, 0)]
            a[dead] = -1
            a[:] = np.take_along_axis(a, np.argsort(a < 0, axis=1, kind="stable"), 1)
        if not live[graph.entry]:
            graph.entry = int(np.flatnonzero(live)[0])
        insert(np.arange(next_in, min(n, next_in + step)))
        next_in = min(n, next_in + step)
        out.append((c, "updated", recall(graph, live)))
        if c in (1, rounds):
            ids = np.flatnonzero(live)
            fresh = G.construct(C.ExactCodec(), Points(x[ids]), np.zeros(len(ids), np.int64), CANDIDATES, degree, "batched", 1, 0.0, 64)
            found, _ = beam(fresh, 0, queries, np.full(len(queries), fresh.entry), ef)
            truth = np.argsort(((queries[:, None, :] - x[ids][None]) ** 2).sum(-1), axis=1)[:, :k]
            out.append((c, "rebuilt", float(np.mean([len(set(t) & set(b[:k])) / k for t, b in zip(truth.tolist(), found.tolist(), strict=True)]))))
    return out


@query()
def update_cycles(spark, d):
    """Twenty cycles of deleting and inserting a share of a segment, against building it anew."""
    base, q = split(spark, d)
    asks = spark.sparkContext.broadcast(np.stack([np.array(r[0]) for r in q.where("vec_id % 50 = 0").orderBy("vec_id").select("vec").collect()]))

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(rows.sort_values("vec_id")["vec"].to_numpy()).astype(np.float64)
        return pd.DataFrame(cycles(x, asks.value, 20, 0.05, 8, ef=32), columns=["cycle", "kind", "recall"])

    return G.assign_segments(base.select("vec_id", "vec"), G.segment_count(base.count(), 2000)).groupBy("segment").applyInPandas(run, "cycle int, kind string, recall double").groupBy("cycle", "kind").agg(F.avg("recall").alias("recall"))


@query()
def deletes_and_rebuild(spark, d):
    """Recall of an index of four segments when a tenth of its rows is deleted: the old graph with the deleted rows left out, the segments built anew, and the codec trained anew."""
    index, q = index_for(spark, d, "acc", segments=4)
    gone = index.vectors.where("vec_id % 10 = 1").select("vec_id")
    less, out = index.delete(gone), None
    truth = stored(E.exact_knn(less.live(), q, K), "truth")
    for name, one in (("deleted", less), ("rebuilt", less.rebuilt()), ("refitted", less.rebuilt(refit=True))):
        row = M.recall(truth, S.search(one, q, K, EF, "codes+rerank"), K).select(F.lit(name).alias("state"), "recall")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def drift_trigger(spark, d):
    """Whether new vectors ask for a rebuild: vectors of the same kind do not, vectors turned round and stretched in some dimensions do."""
    from ..operators import theory as T
    from ..streaming.ingest import needs_rebuild

    base, q = split(spark, d)
    codec = C.ScalarCodec(4).fit(base)
    reference = T.preserved_fraction(T.margins(T.sample_triples(base, 500, 0), codec)).first()["strict"]
    other = base.withColumn("vec", F.transform("vec", lambda x, i: x * (1 + 40 * (i % 2)) + 3))
    return spark.createDataFrame([("same", needs_rebuild(base, codec, reference)), ("other", needs_rebuild(other, codec, reference))], "vectors string, rebuild boolean")


@query()
def graph_reports(spark, d):
    """Degree, reach and recall of the graph that each codec builds, searched by full distances: the quality of the graph apart from the codes. Vertices without
    neighbours count as of degree 0; reach is the share of all vertices that the entry of their segment reaches."""
    out = None
    base, q = split(spark, d)
    truth = stored(E.exact_knn(base, q, K), "truth")
    for name in ("lg", "sq", "pca", "pq", "acc"):
        index = S.build_index(base.select("vec_id", "vec"), codec_named(name), CANDIDATES, DEGREE)
        edges = index.adjacency.where("layer = 0").agg(F.avg(F.size("nbrs")).alias("mean_degree"))
        reach = S.reach(index, full=True).agg((F.sum("reached") / F.sum("n")).alias("reach"))
        one = M.recall(truth, S.search(index, q, K, EF, "exact"), K).join(edges, how="cross").join(reach, how="cross").select(F.lit(name).alias("method"), "recall", "mean_degree", "reach")
        out = one if out is None else out.unionByName(one)
    return out


@query()
def table_function(spark, d):
    """The search as a table function in SQL."""
    from .planner import register_search

    index, q = index_for(spark, d, "acc")
    register_search(spark, index)
    q.select("vec_id", "vec").createOrReplaceTempView("asked")
    return spark.sql("SELECT * FROM graph_search(TABLE(SELECT vec_id, vec FROM asked), 10, 64)")


@query()
def stored_index(spark, d):
    """Save, load, and search the loaded index; adjacency through the custom data source is counted too."""
    from ..sources.datasource import register
    from ..sources.index_store import load_index, save_index
    from ..sources.tables import shared_dir

    index, q = index_for(spark, d, "acc", segments=2)
    path = shared_dir(spark, "index")
    save_index(index, path)
    register(spark)
    lists = spark.read.format("vecgraph").load(path.removeprefix("file://")).groupBy("segment").agg(F.count("*").alias("lists"))
    found = S.search(load_index(spark, path), q, K, EF, "codes+rerank")
    return neat(found).join(lists.agg(F.sum("lists").alias("lists")), how="cross")


@query()
def latency_budget(spark, d):
    """The best recall of each method within a budget of distances per query."""
    from ..operators.measures import recall_at_latency
    from .workloads import Setting, dataset, run_grid

    runs = run_grid(spark, "latency", "embeddings", dataset(spark, d, "embeddings"), [Setting(m, efs=(8, 32, 128), ks=(1,)) for m in ("LG", "LG-ACC")])
    wide = runs.withColumn("ef", F.col("params")["ef"]).where("ef is not null").groupBy("method", "ef").pivot("metric", ["recall", "distances_per_query"]).agg(F.first("value"))
    return recall_at_latency(wide.select("method", F.col("distances_per_query").alias("latency"), "recall"), 300.0)


@query()
def worked_insertion(spark, d):
    """Insertion with a candidate set of four and two neighbours, followed for every vector whose id is divisible by 50 among its seven nearest of all vectors:
    the candidate set after each step, the selection, and what was evaluated."""
    from .worked import insertion

    v = emb(spark, d).select("vec_id", "vec")
    near = E.exact_knn(v, v.where("vec_id % 50 = 0"), 7).join(v, "vec_id")

    def steps(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("rank")
        got = insertion(rows["vec_id"].to_numpy(), np.stack(rows["vec"].to_numpy()), rows["dist"].to_numpy())
        return pd.DataFrame([(rows["query_id"].iloc[0], *r) for r in got], columns=["query_id", "step", "what", "vertices"])

    return near.groupBy("query_id").applyInPandas(steps, "query_id long, step int, what string, vertices string")
