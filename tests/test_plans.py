import pytest

from vecgraph.operators import codecs as C
from vecgraph.operators import exact as E
from vecgraph.operators.measures import plan_cost
from vecgraph.sources.tables import load
from vecgraph.sources.vectors import embedding_vectors, split_queries


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_codes_and_tables_need_one_python_stage(spark, sf):
    v = embedding_vectors(spark, sf)
    c = C.AlignedCodec(8, iters=1, sample=0).fit(v)
    assert plan_cost(c.encode_with_tables(v).select("vec_id", "code", "adt"))["python"] == 1


def test_scan_reads_only_what_is_asked(spark, sf):
    assert "ReadSchema: struct<doc_id:bigint>" in plan(load(spark, sf, "documents", "doc_id"))
    assert "PushedFilters: [IsNotNull(vec_id), GreaterThan(vec_id,5)]" in plan(load(spark, sf, "embeddings", "vec_id").where("vec_id > 5"))


def test_exact_search_shuffles_only_winners(spark, sf):
    base, q = split_queries(embedding_vectors(spark, sf))
    got = E.exact_knn(base, q, 10)
    p = plan(got)
    assert "WindowGroupLimit" in p and plan_cost(got)["exchanges"] == 1 and "CartesianProduct" not in p


def test_rerank_has_no_cartesian(spark, sf):
    base, q = split_queries(embedding_vectors(spark, sf))
    cands = E.exact_knn(base, q, 20).select("query_id", "vec_id")
    assert "CartesianProduct" not in plan(E.rerank(cands, base, q, 5)) and "NestedLoop" not in plan(E.rerank(cands, base, q, 5))


@pytest.mark.parametrize("name", ["exact_knn", "bulk_graph", "adt_quantised", "event_sessions", "doc_trigram_vectors"])
def test_query_equals_its_sql(spark, name):
    import duckdb

    from vecgraph import queries

    d = "/root/testdata/sf0.01"
    got = queries.QUERIES[name](spark, d)
    con = duckdb.connect()
    for t in ("embeddings", "events", "documents"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    want = con.sql(queries.SQL[name])
    cols = sorted(got.columns)
    assert sorted(want.columns) == cols
    same = lambda rows: sorted(tuple(map(str, r)) for r in rows)
    assert same(got.select(*cols).collect()) == same(want.select(*cols).fetchall())


@pytest.mark.parametrize("name", ["sql_functions", "sql_surface"])
def test_pair_queries_fold_in_a_kernel_and_equal_their_sql(spark, name, monkeypatch):
    from vecgraph import queries

    d = "/root/testdata/sf0.01"
    p = plan(queries.QUERIES[name](spark, d))
    assert "MapInArrow" in p and "NestedLoop" not in p and "Cartesian" not in p  # lambdas would be evaluated for every pair
    test_query_equals_its_sql(spark, name)
    monkeypatch.setattr(E, "BLOCK_BYTES", 2048)  # more queries than one block holds
    assert queries.QUERIES[name](spark, d).count() == 10 * 499


def test_boxed_search_equals_the_scan_and_skips_most_rows(spark, monkeypatch):
    import numpy as np

    r = np.random.default_rng(3)
    x = np.concatenate([r.normal(size=(3000, 3)), np.round(r.normal(size=(700, 3)), 1), np.ones((40, 3))])
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, vec array<double>").repartition(3)
    asked = rows.where("vec_id % 37 = 0")
    monkeypatch.setattr(E, "BOX_ROWS", 500)
    pick = lambda df: sorted((a["query_id"], a["rank"], a["vec_id"], a["dist"]) for a in df.collect())
    assert pick(E.boxed_knn(rows, asked, 4)) == pick(E.exact_knn(rows, asked, 4))
    boxes, q = E.Boxes(np.arange(len(x)), x), x[:20]
    assert (np.sort(boxes.ids[boxes.real]) == np.arange(len(x))).all()
    third = np.sort(((q[:, None] - x[None]) ** 2).sum(-1), axis=1)[:, 3]
    assert (boxes.bounds(q) <= third[:, None]).mean() < 0.5
