"""The experiments, re-expressed on the given tables. Every workload returns runs in long form:
(workload, dataset, method, params, metric, value).

A grid of settings runs as one job: codecs are fitted on the whole data set first, then every (setting, segment) is a task that encodes, builds, and searches with all
held-out queries, whose truth comes from the exact scan; what the segments find is merged before it is measured. Segments are bounded, so a task is, whatever the size of
the data set. A segment's vectors and the queries travel as packed arrays. Times are taken inside the task; building time of coded
methods includes fitting and coding. Product codes have 8 bits a subspace; candidate sets hold 64
and lists 16, as a graph of 1,024 and 32 takes numpy hours."""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import codecs as C
from ..operators import exact as E
from ..operators import graph as G
from ..operators import theory as T
from ..operators.kernels import Points, descend, early_abort, reached
from ..queries import query
from ..sources import vectors as X
from ..sources.tables import load, stored

TASKS, SPREAD = 1 << 14, 4  # partitions of a grid at most, and for each build, so that few share one
ASKED = 50  # workloads on whole tables hold out the ids divisible by it
RUNS = "workload string, dataset string, method string, params map<string,string>, metric string, value double"
SETS = {"embeddings": X.embedding_vectors, "docvec": X.document_vectors, "pagevec": X.page_vectors, "linevec": X.lineitem_vectors, "ordervec": X.order_vectors, "uservec": X.user_vectors, "convvec": X.conversation_vectors, "benchvec": X.benchmark_vectors}
METHODS = {
    "LG": lambda **p: C.ExactCodec(),
    "LG-SQ": lambda **p: C.ScalarCodec(**({"bits": 8} | p)),
    "LG-PCA": lambda **p: C.PrincipalCodec(**({"alpha": 0.9} | p)),
    "LG-PQ": lambda **p: C.ProductCodec(**({"m": 16, "bits": 8, "iters": 2, "sample": 0} | p)),
    "LG-ACC": lambda **p: C.AlignedCodec(**({"m": 16, "iters": 3, "sample": 0, "rule": "quantile", "rounding": "nearest"} | p)),
}


@dataclass
class Setting:
    method: str
    codec: dict = field(default_factory=dict)
    candidates: int = 64
    degree: int = 16
    strategy: str = "batched"
    efs: tuple = (16, 64)
    modes: tuple = ("codes+rerank",)
    ks: tuple = (1, 10)
    tau: float = 0.0
    batch: int = 256
    stop: int = 0
    eps: float = 0.0
    profile: bool = False
    label: dict = field(default_factory=dict)

    def params(self) -> dict[str, str]:
        return {k: str(v) for k, v in ({"C": self.candidates, "R": self.degree, "strategy": self.strategy} | self.codec | self.label).items()}


def dataset(spark: SparkSession, d: str, name: str, rows: int | None = None) -> DataFrame:
    v = SETS[name](spark, d).select("vec_id", "vec")
    return C.stable_sample(v, rows) if rows else v


class Timed:
    """A distance source whose time is summed."""

    def __init__(self, inner):
        self.inner, self.seconds = inner, 0.0
        self.n = inner.n
        for name in ("m", "offset", "codes", "x", "block"):
            if hasattr(inner, name):
                setattr(self, name, getattr(inner, name))

    def _call(self, name: str, *a):
        t = time.perf_counter()
        out = getattr(self.inner, name)(*a)
        self.seconds += time.perf_counter() - t
        return out

    def of(self, s, ids):
        return self._call("of", s, ids)

    def pair(self, a, b):
        return self._call("pair", a, b)

    def some(self, s, rows, ids):
        return self._call("some", s, rows, ids)

    def among(self, at, s):
        return self._call("among", at, s)

    def pairs(self, a, b):
        return self._call("pairs", a, b)

    def look_up(self, s, o):
        return self._call("look_up", s, o)

    def summed(self, s, rows, o):
        return self._call("summed", s, rows, o)

    def own(self, at):
        return self.inner.own(at)


def unit_of(codec) -> float:
    """The true distance that one step of the root of a code distance stands for: table entries are whole numbers of a step of squared distance."""
    return (codec.range / (2**codec.table_bits - 1)) ** 0.5 if getattr(codec, "table_bits", None) else 1.0


FOUND_BY = "run int, segment int, n long, ef int, mode string, block int, metric string, value double, found binary, own binary, far binary, truth binary, best binary"


def one_run(x: np.ndarray, ids: np.ndarray, codec, s: Setting, blocks: list[tuple], fit_seconds: float) -> Iterator[dict]:
    """Build one segment and search it for every block (number, queries, truth, its distances): rows of its metrics, and of what each block found in it,
    by the distances of the mode, with true distances and the truth beside it."""
    t = time.perf_counter()
    source = codec.source(x)
    coding = time.perf_counter() - t + fit_seconds if s.method != "LG" else 0.0
    levels = np.zeros(len(x), np.int64)
    if s.strategy not in ("bulk", "spanning"):
        h = ((ids % (1 << 31)) * 2654435761 + 42) % (1 << 32)
        levels = np.floor(-np.log((h + 1) / float(1 << 32)) / np.log(s.degree)).astype(np.int64)
    timed = Timed(source) if s.profile else source
    t = time.perf_counter()
    graph = G.construct(codec, timed, levels, min(s.candidates, max(1, len(x) - 1)), s.degree, s.strategy, 2, s.tau / unit_of(codec), s.batch)
    build = time.perf_counter() - t
    edges = sum(int((a >= 0).sum()) for a in graph.adj)
    per_edge = 4 + (codec.bytes_per_vector() if codec.name == "acc" else 0)
    own = {"coding_seconds": coding, "graph_seconds": build, "total_seconds": coding + build, "edges": edges, "reached": float(reached(graph).mean()), "index_bytes": len(x) * float(codec.bytes_per_vector()) + edges * per_edge} | graph.count
    if s.profile:
        own["distance_share"] = timed.seconds / max(build, 1e-9)
        graph.source = source
    yield from ({"metric": k, "value": float(v)} for k, v in own.items())
    full, asked = Points(x), sum(len(q) for _, q, _, _ in blocks)
    for ef in s.efs:
        keep, took, count = min(ef, max(s.ks)), dict.fromkeys(s.modes, 0.0), {mode: Counter() for mode in s.modes}
        for number, q, truth, best in blocks:
            walked = None  # the walk by codes, which the modes by codes share
            for mode in s.modes:
                t, graph.count = time.perf_counter(), Counter()
                if mode == "exact":
                    kept, graph.source, inline, graph.inline = graph.source, full, graph.inline, None
                    found, dist = descend(graph, q, ef, window=s.stop)
                    graph.source, graph.inline = kept, inline
                elif s.eps:
                    turn = np.linalg.qr(np.random.default_rng(5).normal(size=(x.shape[1],) * 2))[0]
                    kept, graph.source, inline, graph.inline = graph.source, Points(x @ turn), graph.inline, None
                    found, dist = descend(graph, q @ turn, ef, window=s.stop, measure=early_abort(graph.source.x, q @ turn, 16, s.eps, graph.count))
                    graph.source, graph.inline = kept, inline
                else:
                    if walked is None:
                        got = descend(graph, codec.query_state(q), ef, window=s.stop)
                        walked, t = (got, graph.count, time.perf_counter() - t), time.perf_counter()
                    found, dist = walked[0]
                    graph.count = walked[1]
                    took[mode] += walked[2]
                    if mode == "codes+rerank" and codec.name != "exact":
                        dist = np.where(found >= 0, full.of(q, found), np.inf)
                        order = np.lexsort((found, dist), axis=1)
                        found, dist = np.take_along_axis(found, order, 1), np.take_along_axis(dist, order, 1)
                took[mode] += time.perf_counter() - t
                count[mode].update(graph.count)
                found, dist = (np.pad(y[:, :keep], ((0, 0), (0, max(0, keep - y.shape[1]))), constant_values=v) for y, v in ((found, -1), (dist.astype(np.float64), np.inf)))
                at = np.maximum(found, 0)
                far = np.sqrt(np.where(found >= 0, full.of(q, at), np.inf))
                yield {"ef": ef, "mode": mode, "block": number, "found": np.where(found >= 0, ids[at], -1).astype(np.int64).tobytes(), "own": np.where(found >= 0, dist, np.inf).tobytes(), "far": far.tobytes(), "truth": truth.tobytes(), "best": best.tobytes()}
        for mode in s.modes:
            counted = {"search_seconds": took[mode], "distances_per_query": (count[mode]["distances"] or count[mode]["dimensions"] / x.shape[1]) / max(1, asked), "hops_per_query": count[mode]["hops"] / max(1, asked), "asked": asked}
            yield from ({"ef": ef, "mode": mode, "metric": k, "value": float(v)} for k, v in counted.items())


def nearest_of_segments(found: list[np.ndarray], own: list[np.ndarray], far: list[np.ndarray], k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, true distances) of the k best over all segments, by the distances of the mode, ties to the first found."""
    found, own, far = (np.concatenate(y, axis=1) for y in (found, own, far))
    order = np.argsort(own, axis=1, kind="stable")[:, :k]
    return np.take_along_axis(found, order, 1), np.take_along_axis(far, order, 1)


def measured(rows: pd.DataFrame, s: Setting) -> Iterator[tuple[str, str, float, float]]:
    """(k, metric, sum, weight) of what all segments found for one block of queries."""
    keep = min(int(rows["ef"].iloc[0]), max(s.ks))
    parts = [[np.frombuffer(x, kind).reshape(-1, keep) for x in rows[c]] for c, kind in (("found", np.int64), ("own", np.float64), ("far", np.float64))]
    truth = np.frombuffer(rows["truth"].iloc[0], np.int64).reshape(len(parts[0][0]), -1)
    best = np.frombuffer(rows["best"].iloc[0]).reshape(truth.shape)
    for k in (k for k in s.ks if k <= keep):
        ids, far = nearest_of_segments(*parts, k)
        yield str(k), "recall", sum(len(set(a) & set(b)) / k for a, b in zip(ids.tolist(), truth[:, :k].tolist(), strict=True)), len(ids)
        far = np.sort(far, axis=1)[:, : truth.shape[1]]
        with np.errstate(divide="ignore", invalid="ignore"):
            ratio = np.where((far == 0) & (best[:, :k] == 0), 1.0, far / best[:, :k])
        ratio = ratio[np.isfinite(ratio)]
        yield str(k), "distance_ratio", float(ratio.sum()), len(ratio)


def of_segments(rows: pd.DataFrame) -> Iterator[tuple[str, float]]:
    """(metric, value) of all segments of one run: counts, bytes and seconds of work are summed, shares weighted, queries a second taken over the summed seconds."""
    by = {m: (g["value"].to_numpy(), g["n"].to_numpy()) for m, g in rows.groupby("metric")}
    for m, (value, n) in by.items():
        if m == "reached":
            yield m, float((value * n).sum() / n.sum())
        elif m == "distance_share":
            whole = rows[rows["metric"] == "graph_seconds"].set_index("segment")["value"]
            weight = whole.loc[rows[rows["metric"] == m]["segment"]].to_numpy()
            yield m, float((value * weight).sum() / max(weight.sum(), 1e-9))
        elif m == "search_seconds":
            yield "qps", float(by["asked"][0].max() / max(value.sum(), 1e-9))
        elif m != "asked":
            yield m, float(value.sum())


def run_grid(spark: SparkSession, workload: str, name: str, vectors: DataFrame, settings: list[Setting], segments: int | None = None, repeats: int = 1, apart: bool = False, modulus: int = X.HELD_OUT) -> DataFrame:
    """Runs of all settings on one data set, in as many segments as bound each (`default_segments`) unless told otherwise: every segment is searched with every query,
    and recall and ratio are those of the merged results. apart: metrics of each segment by itself, without recall. Ids divisible by `modulus` are the queries."""
    base, queries = X.split_queries(vectors, modulus)
    base, queries = stored(base, "grid-base"), stored(queries, "grid-queries")
    segments, rows_in_all = segments or G.default_segments(base), base.count()
    kmax = max(k for s in settings for k in s.ks)
    near = E.exact_knn(base, queries, kmax).groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("rank", "vec_id", "dist"))).alias("near"))
    asks = queries.join(near, queries["vec_id"] == near["query_id"]).select(F.col("vec_id").alias("id"), "vec", F.col("near.vec_id").alias("truth"), F.col("near.dist").alias("far"))
    fitted = []
    for s in settings:
        t = time.perf_counter()
        codec = METHODS[s.method](**s.codec).fit(base)
        fitted.append((s, codec, time.perf_counter() - t))
    sent = spark.sparkContext.broadcast(fitted)

    def pack(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("id").combine_chunks()
        raw = lambda c: [np.array(rows[c].to_pylist()).tobytes()] if c in rows.column_names else pa.nulls(1, pa.binary())
        return pa.table({"segment": rows["segment"][:1], "ids": [rows["id"].to_numpy().tobytes()], "vecs": [C.matrix(rows["vec"]).tobytes()], "truth": raw("truth"), "far": raw("far")})

    kind = "segment int, ids binary, vecs binary, truth binary, far binary"
    placed = G.assign_segments(base, segments).select("segment", F.col("vec_id").alias("id"), "vec")
    blocks = stored(placed.groupBy("segment").applyInArrow(pack, kind), "grid-segments")
    pieces = F.pmod(F.xxhash64("id"), F.lit(max(1, -(-queries.count() // 4096)))).cast("int")
    asked = stored(asks.withColumn("segment", pieces).groupBy("segment").applyInArrow(pack, kind), "grid-asked")
    runs = F.explode(F.sequence(F.lit(0), F.lit(len(settings) * repeats - 1))).alias("run")
    left = blocks.select("segment", "ids", "vecs", runs)
    right = asked.select(F.col("segment").alias("block"), F.explode(F.sequence(F.lit(0), F.lit(segments - 1))).alias("segment"), "vecs", "truth", "far").select("*", runs)
    columns = [c.split()[0] for c in FOUND_BY.split(", ")]

    def run(key: tuple, own: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        if not len(own) or not len(asked):
            return pd.DataFrame(columns=columns)
        n, which = int(key[0]), int(key[1])
        s, codec, seconds = sent.value[n % len(settings)]
        ids = np.frombuffer(own["ids"].iloc[0], np.int64)
        x = np.frombuffer(own["vecs"].iloc[0]).reshape(len(ids), -1)
        parts = []
        for number, vecs, truth, far in zip(asked["block"], asked["vecs"], asked["truth"], asked["far"], strict=True):
            q = np.frombuffer(vecs).reshape(-1, x.shape[1])
            parts.append((number, q, np.frombuffer(truth, np.int64).reshape(len(q), -1), np.frombuffer(far).reshape(len(q), -1)))
        got = pd.DataFrame(one_run(x, ids, codec, s, parts, seconds / segments), columns=columns)
        return got.assign(run=n, segment=which, n=len(ids))

    def merge(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        s = sent.value[int(key[0]) % len(settings)][0]
        if rows["metric"].isna().all():
            got = list(measured(rows, s))
        elif apart:
            got = [(str(r.segment), r.metric, r.value, r.n) for r in rows.itertuples()]
        else:
            got = [(None, m, v, 1.0) for m, v in of_segments(rows)]
        return pd.DataFrame([(*key[:3], *g) for g in got], columns=["run", "ef", "mode", "k", "metric", "total", "weight"])

    def named(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            out = []
            for r in rows.itertuples():
                s = settings_of[r.run % len(settings)]
                more = {"n": str(int(r.weight) if apart else rows_in_all), "repeat": str(r.run // len(settings))} | ({"segment": r.k} if apart else {"segments": str(segments)})
                more |= {} if r.mode is None else {"ef": str(int(r.ef)), "mode": r.mode}
                more |= {} if r.k is None or apart else {"k": r.k}
                value = r.total if apart else r.total / r.weight if r.weight else 0.0
                out.append((workload, name, s.method, s.params() | more, r.metric, float(value)))
            yield pd.DataFrame(out, columns=["workload", "dataset", "method", "params", "metric", "value"])

    settings_of = settings
    # a build is long and its rows few: Spark would put as many builds in a task as make up its size
    tasks = min(TASKS, SPREAD * len(settings) * repeats * segments)
    left, right = (y.repartition(tasks, "run", "segment") for y in (left, right))
    found = left.groupBy("run", "segment").cogroup(right.groupBy("run", "segment")).applyInPandas(run, FOUND_BY)
    found = found.where("metric is not null") if apart else found
    parts = found.groupBy("run", "ef", "mode", "block").applyInPandas(merge, "run int, ef int, mode string, k string, metric string, total double, weight double")
    whole = parts if apart else parts.groupBy("run", "ef", "mode", "k", "metric").agg(F.sum("total").alias("total"), F.sum("weight").alias("weight"))
    return whole.mapInPandas(named, RUNS)


def rows_of(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RUNS)


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


ALL = tuple(METHODS)


@query()
def w01_profile(spark, d):
    """Share of distance work in building on full vectors, inserted one after another and in batches, on two data sets."""
    return union([run_grid(spark, "w01", n, dataset(spark, d, n, 2000), [Setting("LG", strategy=s, profile=True, efs=(16,), candidates=64, degree=16) for s in ("sequential", "batched")]) for n in ("embeddings", "docvec")])


@query()
def w03_pq_sweep(spark, d):
    """Product codes: bits at 8 subspaces, subspaces at 8 bits."""
    grid = [{"m": 8, "bits": b} for b in (2, 4, 6, 8)] + [{"m": m, "bits": 8} for m in (2, 4, 16, 32)]
    return run_grid(spark, "w03", "embeddings", dataset(spark, d, "embeddings"), [Setting("LG-PQ", g | {"iters": 2}, modes=("codes", "codes+rerank")) for g in grid], modulus=ASKED)


@query()
def w04_sq_pca_sweep(spark, d):
    """Scalar bits; kept principal components, and how many hold 90% of the variance."""
    grid = [Setting("LG-SQ", {"bits": b}, modes=("codes",)) for b in (2, 4, 8, 16)] + [Setting("LG-PCA", {"dims": k}, modes=("codes",)) for k in (8, 16, 32, 48, 56, 64)]
    kept = [("w04", n, "LG-PCA", {"alpha": "0.9"}, "kept_dimensions", float(C.PrincipalCodec(0.9).fit(dataset(spark, d, n)).kept)) for n in ("embeddings", "docvec")]
    return run_grid(spark, "w04", "embeddings", dataset(spark, d, "embeddings"), grid).unionByName(rows_of(spark, kept))


#: Rows of a data set that the five-way comparison builds graphs of; the tables of lines, orders, events and pages are larger than one machine builds in minutes.
COMPARED_ROWS = 1000


def indexing(spark, d, names=tuple(SETS), rows=COMPARED_ROWS, tune=True, modulus=X.HELD_OUT, **how):
    """Five methods on the data sets: time, size, QPS with recall and distance ratio, on a stated sample of `rows` vectors of each (None: all). Product codes take the
    number of subspaces that keeps most comparisons of sampled triples, as the others of its grid do."""
    out = []
    for n in names:
        v = stored(dataset(spark, d, n, rows), "compared")
        dim = len(v.select("vec").first()[0])
        best = min(16, dim)
        if tune:
            pq, triples = METHODS["LG-PQ"], stored(T.sample_triples(v, 300, 0), "triples")
            kept = {m: T.preserved_fraction(T.margins(triples, pq(m=m).fit(v))).first()["strict"] or 0.0 for m in sorted({min(8, dim), best})}
            best = max(kept, key=lambda m: (kept[m], -m))
        own = {"LG-PQ": {"m": best}, "LG-ACC": {"m": min(16, dim)}}
        out.append(run_grid(spark, "w05", n, v, [Setting(m, own.get(m, {}), modes=("codes", "codes+rerank"), **how) for m in ALL], modulus=modulus))
    return union(out)


@query()
def w05_indexing(spark, d):
    """The five methods on all eight data sets."""
    return indexing(spark, d)


@query()
def w05_speedup(spark, d):
    """Speed-up of building over full vectors, next to the share of distances spared."""
    runs = stored(indexing(spark, d, ("docvec",), None, modulus=ASKED).where(F.col("metric").isin("total_seconds", "graph_seconds")), "speedup-runs")
    base = runs.where("method = 'LG'").select("dataset", "metric", F.col("value").alias("lg"))
    return runs.join(base, ["dataset", "metric"]).select("dataset", "method", "metric", (F.col("lg") / F.col("value")).alias("speedup"))


@query()
def w05_dimensions(spark, d):
    """The speed-up of building over full vectors as the dimension grows: text vectors of 64, 256 and 1,024 dimensions."""
    out = []
    for dim in (64, 256, 1024):
        v = C.stable_sample(X.document_vectors(spark, d, dim).select("vec_id", "vec"), 1500)
        runs = stored(run_grid(spark, "w05", f"docvec-{dim}", v, [Setting(m, efs=(64,)) for m in ALL]).where(F.col("metric").isin("graph_seconds", "distances")), "dimension-runs")
        lg = runs.where("method = 'LG'").select("metric", F.col("value").alias("lg"))
        out.append(runs.join(lg, "metric").select("dataset", "method", "metric", (F.col("lg") / F.col("value")).alias("ratio")))
    return union(out)


@query()
def w06_sizes(spark, d):
    """Bytes of the index of every method on all eight data sets, 400 vectors of each."""
    return indexing(spark, d, rows=400, tune=False, efs=(16,), ks=(1,), candidates=32).where("metric = 'index_bytes'").select("dataset", "method", "value")


@query()
def w07_search_curve(spark, d):
    """QPS against recall."""
    s = [Setting(m, efs=(8, 16, 32, 64, 128), modes=("codes+rerank",)) for m in ALL]
    return run_grid(spark, "w07", "embeddings", dataset(spark, d, "embeddings"), s).where(F.col("metric").isin("qps", "recall"))


@query()
def w08_ratio_curve(spark, d):
    """QPS against the distance ratio, two data sets."""
    s = [Setting(m, efs=(8, 32, 128), modes=("codes+rerank",)) for m in ("LG", "LG-PQ", "LG-ACC")]
    return union([run_grid(spark, "w08", n, dataset(spark, d, n), s, modulus=ASKED).where(F.col("metric").isin("qps", "distance_ratio")) for n in ("embeddings", "docvec")])


@query()
def w09_volume(spark, d):
    """A data set that grows, up to 10,000 lines and to all documents."""
    s = [Setting(m, {"m": 6} if m == "LG-ACC" else {}, efs=(32,), candidates=64, degree=16) for m in ("LG", "LG-ACC")]
    most = stored(dataset(spark, d, "linevec", 10_000), "volume-lines")  # holds the smaller samples
    lines = [run_grid(spark, "w09", f"linevec-{n}", C.stable_sample(most, n), s) for n in (1250, 2500, 5000, 10_000)]
    docs = stored(dataset(spark, d, "docvec"), "volume-documents")
    n = docs.count()
    texts = [Setting(m, efs=(32,), candidates=64, degree=16) for m in ("LG", "LG-ACC")]
    return union(lines + [run_grid(spark, "w09", f"docvec-{x}", C.stable_sample(docs, x), texts, modulus=ASKED) for x in sorted({max(50, n // k) for k in (8, 4, 2, 1)})])


@query()
def w10_segments(spark, d):
    """More segments of equal size, built apart: the sum of their times, the longest, and the wall time of the job that builds them at once."""
    s, out = [Setting(m, {"m": 6} if m == "LG-ACC" else {}, efs=(16,), ks=(1,), candidates=64, degree=16) for m in ("LG", "LG-ACC")], []
    for k in (1, 2, 4, 8):
        for one in s:
            t = time.perf_counter()
            runs = stored(run_grid(spark, "w10", f"linevec-{k}x", dataset(spark, d, "linevec", 1250 * k), [one], segments=k, apart=True), "segment-runs")
            wall = time.perf_counter() - t
            out.append(runs.where("metric = 'graph_seconds'").groupBy("workload", "dataset", "method").agg(F.sum("value").alias("summed_seconds"), F.max("value").alias("longest"), F.count("*").alias("segments")).withColumn("wall_seconds", F.lit(wall)))
    return union(out)


@query()
def w11_register_widths(spark, d):
    """Registers of 128, 256 and 512 bits hold 1, 2 and 4 tables: look-ups of so many subspaces at a time."""
    s = [Setting("LG-ACC", {"block": u // 128}, efs=(64,), label={"register_bits": u}) for u in (128, 256, 512)]
    return run_grid(spark, "w11", "embeddings", dataset(spark, d, "embeddings"), s)


@query()
def w12_implementations(spark, d):
    """Plain search, early abort and relaxed stop, on graphs built on full vectors and on codes."""
    s = [Setting(m, modes=("codes+rerank",), efs=(32, 64), **how, label=label) for m in ("LG", "LG-ACC") for how, label in (({}, {"variant": "plain"}), ({"eps": 2.1}, {"variant": "early_abort"}), ({"stop": 16}, {"variant": "relaxed_stop"}))]
    return run_grid(spark, "w12", "embeddings", dataset(spark, d, "embeddings"), s)


@query()
def w13_algorithms(spark, d):
    """The layered graph and single-layer graphs before and after codes, on two data sets; the relaxed selection has the same tau in true distance on both."""
    kinds = (("batched", 0.0, "layered"), ("spanning", 0.0, "spanning"), ("bulk", 0.01, "relaxed"))
    s = [Setting(m, strategy=strategy, tau=tau, label={"variant": v, "tau": str(tau)}, candidates=64, degree=16, efs=(16, 32, 64)) for m in ("LG", "LG-ACC") for strategy, tau, v in kinds]
    return union([run_grid(spark, "w13", n, dataset(spark, d, n, 3000), s) for n in ("embeddings", "docvec")])


@query()
def w14_cache_layout(spark, d):
    """Misses of a model of the first-level cache with codes apart from and beside the ids, on a segment larger than the cache."""
    from .graph_queries import traces

    v = dataset(spark, d, "linevec", 6000)
    base, q = X.split_queries(v)
    codec = METHODS["LG-ACC"](m=6).fit(base)
    asks = np.stack([np.array(r[0]) for r in C.stable_sample(q, 20).select("vec").collect()])
    sent = spark.sparkContext.broadcast((codec, asks))

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        codec, asks = sent.value
        found = traces(np.stack(rows.sort_values("vec_id")["vec"].to_numpy()).astype(np.float64), codec, asks, 16)
        return pd.DataFrame([("w14", "linevec", layout, {}, "miss_rate", m / max(1, a)) for layout, m, a in found] + [("w14", "linevec", layout, {}, "misses", float(m)) for layout, m, a in found], columns=["workload", "dataset", "method", "params", "metric", "value"])

    return G.assign_segments(base, 1).groupBy("segment").applyInPandas(run, RUNS)


@query()
def w15_batched_lookup(spark, d):
    """Table look-ups of a whole candidate list at once and one by one: same sums, seconds of each; and building with insertions one by one and in batches."""
    v = dataset(spark, d, "embeddings")
    codec = METHODS["LG-ACC"]().fit(v)
    sent = spark.sparkContext.broadcast(codec)

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        c = sent.value
        x = np.stack(rows.sort_values("vec_id")["vec"].to_numpy()).astype(np.float64)
        source = c.source(x)
        ids = np.random.default_rng(1).integers(0, len(x), (200, 32))
        state = source.own(np.arange(200) % len(x))
        t = time.perf_counter()
        a = source.of(state, ids)
        whole = time.perf_counter() - t
        t = time.perf_counter()
        b = np.array([[sum(int(state[i, m, source.codes[y, m]]) for m in range(source.m)) for y in row] for i, row in enumerate(ids)])
        single = time.perf_counter() - t
        return pd.DataFrame([("w15", "embeddings", "batched", {}, "seconds", whole), ("w15", "embeddings", "single", {}, "seconds", single), ("w15", "embeddings", "both", {}, "equal", float((a == b).all()))], columns=["workload", "dataset", "method", "params", "metric", "value"])

    looked = G.assign_segments(v, 1).groupBy("segment").applyInPandas(run, RUNS)
    built = run_grid(spark, "w15", "embeddings", dataset(spark, d, "embeddings", 1500), [Setting("LG-ACC", batch=b, strategy="batched" if b > 1 else "sequential", candidates=64, degree=16, efs=(32,), label={"batch": str(b)}) for b in (1, 16, 256)])
    return looked.unionByName(built.where(F.col("metric").isin("graph_seconds", "recall")))


@query()
def w16_coding_share(spark, d):
    """Coding against total time of aligned codes."""
    runs = run_grid(spark, "w16", "docvec", dataset(spark, d, "docvec"), [Setting("LG-ACC", efs=(32,))], modulus=ASKED)
    p = runs.where(F.col("metric").isin("coding_seconds", "total_seconds")).groupBy("workload", "dataset", "method").pivot("metric", ["coding_seconds", "total_seconds"]).agg(F.first("value"))
    return p.withColumn("share", F.col("coding_seconds") / F.col("total_seconds"))


@query()
def w17_profile_codes(spark, d):
    """Share of distance work in building on aligned codes."""
    return run_grid(spark, "w17", "docvec", dataset(spark, d, "docvec"), [Setting(m, strategy="batched", profile=True, efs=(16,)) for m in ("LG", "LG-ACC")], modulus=ASKED).where(F.col("metric").isin("distance_share", "graph_seconds"))


@query()
def w18_acc_sweep(spark, d):
    """Kept dimensions at 16 subspaces and subspaces at all 64 dimensions, on isotropic and on compressible vectors; the recall of each within one latency."""
    grid = [{"dims": k, "m": 16} for k in (16, 32, 48, 64)] + [{"dims": 64, "m": m} for m in (4, 8, 32, 64)]
    runs = run_grid(spark, "w18", "embeddings", dataset(spark, d, "embeddings"), [Setting("LG-ACC", g, efs=(16, 32, 64, 128)) for g in grid])
    texts = run_grid(spark, "w18", "docvec", dataset(spark, d, "docvec", 3000), [Setting("LG-ACC", {"dims": k, "m": 16}, efs=(16, 32, 64, 128)) for k in (16, 32, 64, 128, 256)])
    runs = stored(runs.unionByName(texts), "sweep-runs")
    # the best recall@10 of each setting within one time a query: that of the median setting at ef 64
    of = lambda m: runs.where(F.col("metric") == m).where("params['ef'] is not null and coalesce(params['k'], '10') = '10'").select("dataset", F.col("params")["dims"].alias("dims"), F.col("params")["m"].alias("m"), F.col("params")["ef"].alias("ef"), F.col("value").alias(m))
    both = of("recall").join(of("qps"), ["dataset", "dims", "m", "ef"])
    budget = both.where("ef = '64'").groupBy("dataset").agg(F.percentile_approx("qps", 0.5).alias("least_qps"))
    best = both.join(budget, "dataset").where("qps >= least_qps").groupBy("dataset", "dims", "m").agg(F.max("recall").alias("value"))
    return runs.unionByName(best.select(F.lit("w18").alias("workload"), "dataset", F.lit("LG-ACC").alias("method"), F.create_map(F.lit("dims"), F.col("dims"), F.lit("m"), F.col("m")).alias("params"), F.lit("recall_at_latency").alias("metric"), "value"))


@query()
def w19_error_condition(spark, d):
    """How often codes keep the comparison of sampled triples, by codec; near pairs and a near against a far neighbour."""
    v = stored(dataset(spark, d, "embeddings"), "triples-base")
    out = []
    for pair in ((1, 2), (1, 100)):
        tri = stored(T.sample_triples(v, 10_000, 100, pair), "triples")
        for name in ("LG-SQ", "LG-PCA", "LG-PQ", "LG-ACC"):
            got = T.preserved_fraction(T.margins(tri, METHODS[name]().fit(v))).select(F.explode(F.map_from_arrays(F.array(*map(F.lit, ("strict", "ge", "agree", "ties"))), F.array("strict", "ge", "agree", "ties"))).alias("metric", "value"))
            out.append(got.select(F.lit("w19").alias("workload"), F.lit("embeddings").alias("dataset"), F.lit(name).alias("method"), F.create_map(F.lit("pair"), F.lit(str(pair))).alias("params"), "metric", "value"))
    return union(out)


@query()
def w21_constrained(spark, d):
    """Search among rows of some labels: filter first, or fetch more and filter."""
    from .graph_queries import index_for
    from ..operators import measures as M
    from ..operators import search as S

    index, q = index_for(spark, d, "acc")
    where = F.col("label") < 3
    truth = stored(E.filtered_knn(index.vectors, q, where, 10), "truth")
    out = [M.recall(truth, S.search(index, q, 10, 64, "codes+rerank", where=where, policy=p), 10).select(F.lit(p).alias("policy"), "recall") for p in ("pre", "post")]
    return out[0].unionByName(out[1])


@query()
def w22_hypotheses(spark, d):
    """A codec that helps search and not building (scalar codes against full vectors), fewer principal dimensions at equal bits, and fewer bits in table entries, on text vectors."""
    grid = [Setting(m, efs=(16, 64), modes=("codes",), label={"varied": "method"}) for m in ("LG", "LG-SQ")]
    grid += [Setting("LG-ACC", {"dims": k}, efs=(64,), label={"varied": "dims"}) for k in (16, 32, 64, 128, 256)]
    grid += [Setting("LG-ACC", {"table_bits": h, "rule": r, "rounding": o}, efs=(64,), label={"varied": "table_bits"}) for h in (6, 8, 10, 12, None) for r, o in (("sum_of_max", "floor"), ("quantile", "nearest"))]
    return run_grid(spark, "w22", "docvec", dataset(spark, d, "docvec", 3000), grid)


@query()
def w23_ablations(spark, d):
    """Aligned codes without principal axes, without table quantisation, without codes beside the ids, and one subspace at a time, beside the whole method."""
    parts = {"whole": {}, "no principal axes": {"pca": False}, "no table quantisation": {"table_bits": None}, "codes apart from ids": {"inline": False}, "one subspace at a time": {"block": 1}}
    s = [Setting("LG-ACC", how, efs=(32, 64), label={"variant": v}, candidates=64, degree=16) for v, how in parts.items()]
    return union([run_grid(spark, "w23", n, dataset(spark, d, n, 3000), s) for n in ("embeddings", "docvec")])


@query()
def w24_three_runs(spark, d):
    """Building time of each method in three runs: least, median, most."""
    runs = run_grid(spark, "w24", "docvec", dataset(spark, d, "docvec", 2000), [Setting(m, efs=(16,), ks=(1,)) for m in ALL], repeats=3).where("metric = 'total_seconds'")
    return runs.groupBy("workload", "dataset", "method").agg(F.min("value").alias("least"), F.median("value").alias("median"), F.max("value").alias("most"), F.count("*").alias("runs"))


@query("WITH z AS (SELECT row_number() OVER () AS id, l_orderkey, l_linenumber, [" + ", ".join(f"({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER ()" for c in ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE))"]) + "] AS vec FROM lineitem), near AS (SELECT q.id AS query_id, q.l_orderkey, q.l_linenumber, sqrt(list_sum(list_transform(list_zip(q.vec, b.vec), lambda p: (p[1] - p[2]) * (p[1] - p[2])))) AS dist FROM z q JOIN z b ON q.l_orderkey % 1000 = 0 AND b.id <> q.id) SELECT l_orderkey, l_linenumber, CAST(r AS INTEGER) AS rank, round(dist, 4) + 0.0 AS dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist) AS r FROM near) WHERE r <= 3")
def lineitem_knn_sample(spark, d):
    """Nearest lines of a stated set of lines, the orders divisible by 1,000, among all lines."""
    keys = ("l_orderkey", "l_linenumber")
    v = stored(X.line_numbers(load(spark, d, "lineitem"), F.monotonically_increasing_id(), keys), "lines")  # written once, so numbers are fixed
    asked = v.where("l_orderkey % 1000 = 0")
    near = E.boxed_knn(v, asked, 3)
    return near.join(asked.select(F.col("vec_id").alias("query_id"), *keys), "query_id").select(*keys, "rank", (F.round("dist", 4) + F.lit(0.0)).alias("dist"))
