import numpy as np
import pytest
from pyspark.sql import functions as F

from vecgraph.operators import codecs as C
from vecgraph.operators import exact as E
from vecgraph.operators import graph as G
from vecgraph.operators import measures as M
from vecgraph.operators import search as S
from vecgraph.operators.kernels import Points, beam, build_bulk, build_layered, descend, early_abort, lru_misses, reached, select_lists
from vecgraph.plans import planner, worked
from vecgraph.sources.vectors import embedding_vectors, split_queries, validate_vectors


def test_worked_insertion():
    steps = {what: v for _, what, v in worked.run()}
    assert steps["expand 0"] == "5,9,0,13" and steps["expand 5"] == "5,9,15,0"
    assert steps["select"] == "17,5" and steps["evaluated"] == "0,3,5,9,13,15,17"
    assert [v for _, w, v in worked.run() if w.startswith("expand")][-1] == "17,5,3,9"


def points(n=300, d=8, seed=0):
    return np.random.default_rng(seed).normal(size=(n, d))


@pytest.mark.parametrize("batch", [1, 64])
def test_layered_invariants_and_recall(batch):
    x, q = points(400), points(30, seed=1)
    levels = np.floor(-np.log(np.random.default_rng(2).random(400)) / np.log(8)).astype(int)
    g = build_layered(Points(x), levels, 32, 8, batch=batch)
    for layer, a in enumerate(g.adj):
        for v, row in enumerate(a):
            nb = row[row >= 0]
            assert len(set(nb)) == len(nb) and v not in nb and (levels[nb] >= layer).all()
            assert levels[v] >= layer or not len(nb)
    assert reached(g).mean() > 0.99
    found, _ = descend(g, q, 64)
    truth = ((q[:, None] - x[None]) ** 2).sum(-1).argsort(axis=1)[:, :10]
    assert np.mean([len(set(a) & set(b)) / 10 for a, b in zip(found[:, :10], truth, strict=True)]) > 0.95


def test_wide_beam_is_exact():
    x, q = points(200), points(20, seed=3)
    g = build_bulk(Points(x), 199, 12)
    found, dist = beam(g, 0, q, np.full(20, g.entry), 200)
    want = ((q[:, None] - x[None]) ** 2).sum(-1)
    assert (found[:, :5] == want.argsort(axis=1)[:, :5]).all()


def test_duplicates_and_reach():
    x = np.repeat(points(40), 6, axis=0)
    g = build_bulk(Points(x), 16, 6)
    assert reached(g).all()


def test_selection_is_the_fold():
    x = points(60, 4)
    source = Points(x)
    d = source.of(x[:20], np.tile(np.arange(60), (20, 1)))
    d[np.arange(20), np.arange(20)] = np.inf
    ids = d.argsort(axis=1)[:, :30]
    dist = np.take_along_axis(d, ids, 1)
    for tau in (0.0, 0.05):
        got = select_lists(source, ids, dist, 6, tau)
        for r in range(20):
            kept = []
            for v, dv in zip(ids[r], dist[r], strict=True):
                if len(kept) < 6 and not any(np.sqrt(((x[u] - x[v]) ** 2).sum()) < np.sqrt(dv) - 3 * tau for u in kept):
                    kept.append(v)
            assert [v for v in got[r] if v >= 0] == kept


def test_early_abort_with_room_is_exact():
    from collections import Counter

    x, q = points(200, 32), points(10, 32, seed=5)
    g = build_bulk(Points(x), 64, 10)
    want = beam(g, 0, q, np.full(10, g.entry), 32)
    got = beam(g, 0, q, np.full(10, g.entry), 32, measure=early_abort(x, q, 8, 1e9, Counter()))
    assert (want[0] == got[0]).all()
    c = Counter()
    beam(g, 0, q, np.full(10, g.entry), 32, measure=early_abort(x, q, 8, 2.1, c))
    assert c["dimensions"] > 0


@pytest.mark.parametrize("n", [0, 1, 2, 3])
def test_tiny_graphs(n):
    g = build_layered(Points(points(max(n, 1))[:n]), np.zeros(n, int), 4, 2)
    assert len(g.adj[0]) == n


def test_cache_model():
    assert lru_misses(np.array([0, 8, 64, 0, 64])) == (2, 5)
    assert lru_misses(np.arange(0, 1 << 16, 64))[0] == 1024


@pytest.fixture(scope="module")
def parts(spark, sf):
    return split_queries(embedding_vectors(spark, sf))


@pytest.mark.parametrize("codec, mode, floor", [(C.ExactCodec(), "exact", 0.97), (C.ScalarCodec(8), "codes", 0.95), (C.AlignedCodec(16, iters=3, sample=0, rule="quantile", rounding="nearest"), "codes+rerank", 0.85)])
def test_search_recall(parts, codec, mode, floor):
    base, q = parts
    index = S.build_index(base, codec, 64, 16)
    truth = E.exact_knn(base, q, 10)
    assert M.recall(truth, S.search(index, q, 10, 128, mode), 10).first()["recall"] >= floor


def test_segments_merge_to_the_same(parts):
    base, q = parts
    index = S.build_index(base, C.ExactCodec(), 64, 16, segments=3)
    truth = E.exact_knn(base, q, 10)
    assert M.recall(truth, S.search(index, q, 10, 128, "exact"), 10).first()["recall"] >= 0.98
    assert index.adjacency.select("segment").distinct().count() == 3


def test_bulk_graph_invariants(parts):
    base, _ = parts
    r = G.check_graph(G.edges_of(G.bulk_graph(base, 16, 6)), 6).first()
    assert (r["over_degree"], r["loops"], r["repeated"], r["without_list"]) == (0, 0, 0, 0)


def test_filtered_search(parts):
    base, q = parts
    index = S.build_index(base, C.ExactCodec(), 64, 16)
    got = S.search(index, q, 5, 64, "exact", where=F.col("label") < 3, policy="pre")
    assert got.join(base.where("label >= 3"), "vec_id").count() == 0


def test_range_and_exact_edges(spark):
    df = spark.createDataFrame([(0, [0.0, 0.0]), (1, [3.0, 4.0]), (2, [0.0, 1.0]), (3, [0.0, 1.0])], "vec_id long, vec array<double>")
    assert [(r["query_id"], r["vec_id"]) for r in E.range_search(df, df, 1.0).where("query_id < vec_id").orderBy("query_id", "vec_id").collect()] == [(0, 2), (0, 3), (2, 3)]
    near = E.exact_knn(df, df.where("vec_id = 0"), 10).orderBy("rank").collect()
    assert [r["vec_id"] for r in near] == [2, 3, 1] and near[2]["dist"] == 5.0
    assert E.exact_knn(df, df.where("false"), 3).count() == 0
    bad = spark.createDataFrame([(0, [float("nan")]), (0, None)], "vec_id long, vec array<double>")
    r = validate_vectors(bad).first()
    assert (r["n"], r["n_null"], r["n_not_finite"], r["n_repeated_ids"]) == (2, 1, 1, 1)


def test_planner():
    assert planner.choose(10**6, 100, 10).kind == "graph"
    assert planner.choose(10**6, 100, 10, selectivity=0.001).kind == "exact"
    assert planner.choose(3000, 1, 10, ef=512).kind == "code_scan"


def test_frontier_walk_ends_only_without_open_candidates(spark):
    n = 9  # a chain: the nearest vertex is the last, and each round takes one step
    base = spark.createDataFrame([(i, [float(i)]) for i in range(1, n)], "vec_id long, vec array<double>")
    edges = spark.createDataFrame([(i, i + 1) for i in range(1, n - 1)], "src long, dst long")
    q = spark.createDataFrame([(0, [float(n)])], "vec_id long, vec array<double>")
    found = G.frontier_search(edges, base, q, 1, 3).collect()
    assert sorted(r["vec_id"] for r in found) == [n - 3, n - 2, n - 1]
    with pytest.raises(RuntimeError):
        G.frontier_search(edges, base, q, 1, 3, 3)


def test_no_more_than_blocks_reach_the_driver(spark, parts, monkeypatch):
    base, q = parts
    queries = base.select("vec_id", "vec")
    run = {"knn": lambda: E.exact_knn(queries, queries, 3), "range": lambda: E.range_search(queries, queries, 8.0), "mutual": lambda: E.mutual_knn(queries, 3), "scan": lambda: S.code_scan(queries, C.ScalarCodec(8).fit(base), queries, 3)}
    whole = {n: sorted(map(tuple, f().collect())) for n, f in run.items()}
    monkeypatch.setattr(E, "BLOCK_BYTES", 20_000)
    sizes = [len(ids) for ids, _ in E.query_blocks(queries, 512)]
    assert len(sizes) > 2 and sum(sizes) == queries.count() and max(sizes) * 512 <= 2 * 20_000
    for n, f in run.items():
        assert sorted(map(tuple, f().collect())) == whole[n], n
    index = S.build_index(base, C.ExactCodec(), 64, 16)
    assert M.recall(E.exact_knn(base, q, 10), S.search(index, q, 10, 128, "exact"), 10).first()["recall"] >= 0.97


def test_blocks_are_fetched_one_after_another(parts, monkeypatch):
    base, _ = parts
    monkeypatch.setattr(E, "BLOCK_BYTES", 20_000)
    fetched = []
    from pyspark.sql.classic.dataframe import DataFrame as Classic

    before = Classic.toArrow
    monkeypatch.setattr(Classic, "toArrow", lambda self: fetched.append(1) or before(self))
    blocks = E.query_blocks(base.select("vec_id", "vec"), 512)
    next(blocks)
    assert len(fetched) == 1


def test_segments_are_bounded_by_default(spark, parts, monkeypatch):
    base, q = parts
    monkeypatch.setattr(G, "SEGMENT_ROWS", 60)
    index = S.build_index(base, C.ExactCodec(), 32, 8)
    assert index.segments == -(-base.count() // 60) and index.packed().count() == index.segments
    monkeypatch.setattr(G, "SEGMENT_BYTES", 64 * 8 * 20)
    assert G.default_segments(base) == -(-base.count() // 20)
    assert M.recall(E.exact_knn(base, q, 5), S.search(index, q, 5, 64, "exact"), 5).first()["recall"] > 0.98


def test_walks_read_packed_segments_without_a_shuffle(parts):
    base, q = parts
    index = S.build_index(base, C.AlignedCodec(16, iters=2, sample=0), 32, 8, segments=2)
    index.packed()
    assert "Exchange" not in S.walk(index, q, 32)._jdf.queryExecution().executedPlan().toString()


def test_deletes_and_rebuild(spark, parts):
    base, q = parts
    index = S.build_index(base, C.ExactCodec(), 64, 16, segments=3)
    gone = base.where("vec_id % 10 < 3").select("vec_id")
    for less in (index.delete(gone), index.delete(gone).rebuilt(), index.delete(gone).rebuilt(refit=True)):
        truth = E.exact_knn(base.where("vec_id % 10 >= 3"), q, 5)
        found = S.search(less, q, 5, 128, "exact")
        assert found.where("vec_id % 10 < 3").count() == 0 and M.recall(truth, found, 5).first()["recall"] >= 0.95
    one = index.delete(base.where("vec_id = 11").select("vec_id")).rebuilt()
    segment = index.placed().where("vec_id = 11").first()["segment"]
    kept = lambda x: sorted(map(tuple, x.adjacency.where(f"segment <> {segment}").select("segment", "layer", "src").collect()))
    assert kept(one) == kept(index)  # the other segments keep their lists


def test_filtered_walk_returns_k_of_rare_rows(parts):
    base, q = parts
    index = S.build_index(base, C.ExactCodec(), 64, 16)
    where = F.col("vec_id") % 37 == 1
    truth = E.filtered_knn(base, q, where, 3)
    got = S.filtered_search(index, q, where, "post", 3, 4, "exact")
    assert got.groupBy("query_id").count().where("count < 3").count() == 0
    assert M.recall(truth, got, 3).first()["recall"] > 0.8


def test_reachable_ends_by_itself_or_raises(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(30)], "src long, dst long")
    assert G.reachable(edges, 0).count() == 31
    with pytest.raises(RuntimeError):
        G.reachable(edges, 0, rounds=5)


def test_tasks_of_a_build_hold_bounded_arrays(monkeypatch):
    import tracemalloc

    from vecgraph.operators import kernels as N

    x = np.random.default_rng(3).normal(size=(3000, 64))
    tracemalloc.start()
    graph = N.build_bulk(N.Points(x), 16, 8)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 160 << 20  # 256 vertices against all took 393 MB of differences
    monkeypatch.setattr(N, "PIECE_BYTES", 1 << 60)
    assert (N.build_bulk(N.Points(x), 16, 8).adj[0] == graph.adj[0]).all()


def test_tables_larger_than_vectors_are_computed_when_asked_for(spark, parts, monkeypatch):
    base, q = parts
    codec = C.ProductCodec(16, 8, 1, sample=0).fit(base)
    sent = G.prepared(G.assign_levels(G.assign_segments(base, 1), 8), codec)
    assert sent.selectExpr("max(length(tables))").first()[0] == 8 * codec.dim  # and not 16 kB of table
    rows = sent.orderBy("vec_id").toPandas()
    kept = G.source_of(codec, list(rows["code"]), list(rows["tables"]))
    monkeypatch.setattr(C, "TABLES_BYTES", 1 << 12)
    lazy = G.source_of(codec, list(rows["code"]), list(rows["tables"]))
    at, ids = np.arange(7), np.arange(21).reshape(7, 3)
    assert isinstance(kept.tables, np.ndarray) and not isinstance(lazy.tables, np.ndarray)
    assert (kept.of(kept.own(at), ids) == lazy.of(lazy.own(at), ids)).all()
    x = np.frombuffer(b"".join(rows["tables"])).reshape(len(rows), -1)
    assert (C.nearest_centroids(x, codec.books, codec.parts)[0] == codec.codes(x)).all()


def test_insertions_are_followed_on_the_given_vectors(spark, sf):
    from vecgraph.queries import QUERIES

    rows = QUERIES["worked_insertion"](spark, sf).collect()
    v = embedding_vectors(spark, sf)
    nearest = {r["query_id"]: r["vec_id"] for r in E.exact_knn(v, v.where("vec_id % 50 = 0"), 1).collect()}
    chosen = {r["query_id"]: r["vertices"].split(",") for r in rows if r["what"] == "select"}
    assert chosen.keys() == nearest.keys() and all(1 <= len(c) <= 2 for c in chosen.values())
    seen = {r["query_id"]: r["vertices"].split(",") for r in rows if r["what"] == "evaluated"}
    assert all(c[0] == str(nearest[q]) for q, c in chosen.items() if str(nearest[q]) in seen[q])
    assert all(len(r["vertices"].split(",")) <= 4 for r in rows if r["what"].startswith("expand"))


def test_workloads_build_bounded_segments_and_measure_merged_results(spark, sf, monkeypatch):
    from vecgraph.plans import workloads

    v = embedding_vectors(spark, "/root/testdata/sf0.01").select("vec_id", "vec")
    monkeypatch.setattr(G, "default_segments", lambda vectors: G.segment_count(vectors.count(), 100))
    runs = workloads.run_grid(spark, "t", "embeddings", v, [workloads.Setting("LG", efs=(32,), profile=True)]).collect()
    got = {(r["metric"], r["params"].get("k")): r for r in runs}
    assert len(got) == len(runs) and {r["params"]["segments"] for r in runs} == {"5"} and {r["params"]["n"] for r in runs} == {"450"}
    assert got["recall", "10"]["value"] > 0.98 and got["distance_ratio", "10"]["value"] < 1.01 and 0 < got["distance_share", None]["value"] < 1
    apart = workloads.run_grid(spark, "t", "embeddings", v, [workloads.Setting("LG", efs=(32,))], apart=True).where("metric = 'edges'").collect()
    assert sorted(r["params"]["segment"] for r in apart) == list("01234") and sum(int(r["params"]["n"]) for r in apart) == 450
    assert max(int(r["params"]["n"]) for r in apart) < 150


def test_reports_state_reach_and_count_vertices_without_neighbours(spark, sf, monkeypatch):
    from vecgraph.plans import graph_queries
    from vecgraph.queries import QUERIES

    held = []
    build = S.build_index

    def lonely(*args, **how):  # the lists of five vertices, the entry not among them, are taken from each graph, and nobody links to them
        index = build(*args, **how)
        alone = [r[0] for r in index.adjacency.where("layer = 0").orderBy(F.desc("src")).limit(5).select("src").collect()]
        lists = F.when(F.col("src").isin(alone), F.expr("filter(nbrs, x -> false)")).otherwise(F.filter("nbrs", lambda x: ~x["dst"].isin(alone)))
        index.adjacency = index.adjacency.where("layer = 0").withColumn("nbrs", lists)
        held.append(index)
        return index

    monkeypatch.setattr(graph_queries.S, "build_index", lonely)
    got = {r["method"]: r for r in QUERIES["graph_reports"](spark, sf).collect()}
    assert list(got) == ["lg", "sq", "pca", "pq", "acc"]
    for r, index in zip(got.values(), held, strict=True):
        lists = {x["src"]: [y["dst"] for y in x["nbrs"]] for x in index.adjacency.collect()}
        seen, front = set(), {min(lists)}
        while front:
            seen |= front
            front = {y for v in front for y in lists[v]} - seen
        assert r["reach"] == len(seen) / len(lists) <= (len(lists) - 5) / len(lists)
        assert r["mean_degree"] == pytest.approx(sum(map(len, lists.values())) / len(lists))


@pytest.mark.parametrize("name", ["vectors", "tables", "inlined"])
def test_a_walk_measures_only_what_it_has_not_seen(name):
    from vecgraph.operators.kernels import Graph, Tables

    x = points(400)
    source = Points(x)
    if name != "vectors":
        codes = np.abs(x * 5).astype(np.int16) % 16
        between = np.abs(np.arange(16.0)[:, None] - np.arange(16.0)[None, :]).astype(np.float32)
        source = Tables(codes, None, np.tile(between, (8, 1, 1)))
    built = build_layered(source, np.zeros(400, int), 32, 8)
    graph = Graph(400, [16], source, name == "inlined")
    graph.set(0, np.arange(400), built.adj[0])
    graph.entry, graph.top, measured = 0, 0, []
    for one in ("_sum",) if name == "vectors" else ("summed", "look_up"):
        before = getattr(source, one)
        setattr(source, one, lambda *a, before=before: (lambda d: measured.append(d.size) or d)(before(*a)))
    state = source.own(np.arange(30))
    found, dist = beam(graph, 0, state, np.zeros(30, int), 16)
    assert sum(measured) == graph.count["distances"] + 30  # and not every entry of every list
    assert (dist == source.of(state, found)).all() and (np.diff(dist, axis=1) >= 0).all()


def test_many_queries_walk_as_few_do(monkeypatch):
    from vecgraph.operators import kernels as N

    g = build_layered(Points(points(300)), np.zeros(300, int), 32, 8)
    q = points(50, seed=4)
    whole = [descend(g, q, 16, window=w) for w in (0, 8)]
    monkeypatch.setattr(N, "BEAM_ROWS", 7)
    for w, (found, dist) in zip((0, 8), whole, strict=True):
        got = descend(g, q, 16, window=w)
        assert (got[0] == found).all() and (got[1] == dist).all()


def test_modes_by_codes_share_a_walk(monkeypatch):
    from vecgraph.plans import workloads

    x, q = points(200), points(10, seed=2)
    codec = C.ScalarCodec(4)
    codec.lo, codec.step, codec.dim = x.min(axis=0), np.ptp(x, axis=0) / 15, 8
    walks = []
    monkeypatch.setattr(workloads, "descend", lambda *a, **how: walks.append(1) or descend(*a, **how))
    s = workloads.Setting("LG-SQ", efs=(16, 32), modes=("codes", "codes+rerank"))
    truth = np.zeros((10, 10), np.int64)
    rows = list(workloads.one_run(x, np.arange(200), codec, s, [(0, q, truth, truth * 1.0)], 0.0))
    assert len(walks) == 2  # one for each width
    kept = {(r["mode"], r["ef"], r["metric"]): r["value"] for r in rows if "metric" in r and "mode" in r}
    for ef in (16, 32):
        assert kept["codes", ef, "distances_per_query"] == kept["codes+rerank", ef, "distances_per_query"] > 0
        assert kept["codes+rerank", ef, "search_seconds"] > kept["codes", ef, "search_seconds"] > 0


def test_builds_of_a_grid_are_dealt_to_tasks_of_their_own(spark, monkeypatch):
    from vecgraph.plans import workloads

    v = embedding_vectors(spark, "/root/testdata/sf0.01").select("vec_id", "vec")
    runs = workloads.run_grid(spark, "t", "embeddings", v, [workloads.Setting("LG", efs=(16,), ks=(1,)), workloads.Setting("LG-SQ", efs=(16,), ks=(1,))], 3)
    assert "hashpartitioning(run#" in (plan := runs._jdf.queryExecution().executedPlan().toString()) and plan.count(", 24), REPARTITION_BY_NUM") == 2
    assert len({r["method"] for r in runs.collect()}) == 2
