import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from vecgraph.functions import vectors as V
from vecgraph.operators import codecs as C
from vecgraph.operators import measures as M
from vecgraph.operators import theory as T
from vecgraph.sources.vectors import embedding_vectors


def one(spark, expr, **cols):
    names = list(cols)
    kinds = {list: "array<double>", float: "double", int: "int"}
    df = spark.createDataFrame([tuple(cols.values())], ", ".join(f"{n} {kinds[type(cols[n])]}" for n in names))
    return df.select(expr.alias("x")).first()[0]


@pytest.mark.parametrize("v, w, margin", [([1.0, 0.0], [2.0, 0.0], -1.5), ([2.0, 0.0], [1.0, 0.0], 1.5), ([1.0, 0.0], [-1.0, 0.0], 0.0)])
def test_bisector_cases(spark, v, w, margin):
    assert one(spark, V.bisector_margin("u", "v", "w"), u=[0.0, 0.0], v=v, w=w) == margin


vec = st.lists(st.floats(-3, 3, allow_nan=False, width=32), min_size=4, max_size=4).map(np.array)


def np_margin(u, v, w):
    return (w - v) @ u - (w @ w - v @ v) / 2


@settings(max_examples=200, deadline=None)
@given(vec, vec, vec)
def test_lemma_in_numpy(u, v, w):
    diff = ((u - v) ** 2).sum() - ((u - w) ** 2).sum()
    assert abs(diff - 2 * np_margin(u, v, w)) < 1e-6


@settings(max_examples=200, deadline=None)
@given(vec, vec, vec, vec, vec, vec)
def test_error_expansion(u, v, w, a, p, q):
    total = q @ u - p @ u - w @ q + v @ p + (q @ q - p @ p) / 2 + (w - v) @ a - q @ a + p @ a
    assert abs(np_margin(u, v, w) - total - np_margin(u - a, v - p, w - q)) < 1e-6


def test_identity_and_strict_condition(spark, sf):
    v = embedding_vectors(spark, sf)
    for codec in (C.ScalarCodec(4), C.ProductCodec(8, 4, 2, sample=0)):
        rows = T.margins(T.sample_triples(v, 100, 0), codec.fit(v)).collect()
        assert max(abs(r["margin"] - r["err"] - r["code_margin"]) for r in rows) < 1e-9
        strict = [r for r in rows if abs(r["margin"]) > abs(r["err"]) + 1e-12]
        assert strict and all(np.sign(r["margin"]) == np.sign(r["code_margin"]) for r in strict)


def test_same_code_is_a_tie(spark):
    t = spark.createDataFrame([(1, 2, 3, 0.5, 0.5, 0.0)], "u int, v int, w int, margin double, err double, code_margin double")
    r = T.preserved_fraction(t).first()
    assert (r["strict"], r["ge"], r["ties"]) == (0.0, 1.0, 1.0)


def test_recall_and_ratio(spark):
    truth = spark.createDataFrame([(0, 1, 1, 1.0), (0, 2, 2, 2.0), (0, 3, 3, 4.0)], "query_id long, rank int, vec_id long, dist double")
    got = spark.createDataFrame([(0, 1, 2, 2.0), (0, 2, 3, 4.0), (0, 3, 9, 5.0)], "query_id long, rank int, vec_id long, dist double")
    assert M.recall(truth, got, 3).first()["recall"] == pytest.approx(2 / 3)
    assert M.distance_ratio(truth, got, 3).first()["distance_ratio"] == pytest.approx(1.75)
    zero = truth.withColumn("dist", F.lit(0.0))
    assert M.distance_ratio(zero, zero, 3).first()["distance_ratio"] == 1.0


def test_arithmetic(spark):
    plain, codes = M.register_loads(F.lit(768), F.lit(128), F.lit(16), F.lit(8))
    assert spark.range(1).select(plain.cast("int"), codes.cast("int")).first()[:] == (192, 1)
    assert C.code_length(16) == 4 and C.code_length(17) == 5
    assert [r["block"] for r in M.simd_plan(spark, [128], 16).collect()] == [16]
    assert C.ExactCodec.bytes_per_vector(type("D", (), {"dim": 768})()) == 3072


def read_by_tasks(spark, df):
    """The rows of a query, and whether its plan scans the vectors."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return df.collect(), "embeddings.parquet" in plan and "embedding" in plan


def test_access_formula_counts_the_given_vectors(spark, sf):
    from vecgraph.queries import QUERIES

    rows, reads = read_by_tasks(spark, QUERIES["access_formula"](spark, sf))
    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    assert reads and max(r["n"] for r in rows) == n and sum(r["n"] for r in rows) == 2 * n
    assert [r["acquisition_plain"] for r in rows if r["n"] == n] == [pytest.approx(32 * np.log2(n), abs=1e-5)]


def test_register_loads_are_those_of_the_given_vectors(spark, sf):
    from vecgraph.queries import QUERIES

    rows, reads = read_by_tasks(spark, QUERIES["register_loads"](spark, sf))
    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    got = {r["register_bits"]: (r["dim"], r["loads_plain"], r["loads_codes"], r["scan_plain"]) for r in rows}
    assert reads and got == {u: (64, 2048 // u, 1, n * 2048 // u) for u in (128, 256, 512)}


def test_simd_plan_is_that_of_the_given_vectors(spark, sf):
    from vecgraph.queries import QUERIES

    rows, reads = read_by_tasks(spark, QUERIES["simd_plan"](spark, sf))
    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    assert reads and {r["register_bits"]: (r["m"], r["steps"], r["n_steps"]) for r in rows} == {128: (16, 16, 16 * n), 256: (16, 8, 8 * n), 512: (16, 4, 4 * n)}


def test_admission_is_counted_without_a_row_for_each_pair(spark, sf, monkeypatch):
    from vecgraph.operators import exact as E
    from vecgraph.queries import QUERIES

    plan = QUERIES["dc1_admission"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoopJoin" not in plan and "CartesianProduct" not in plan
    base = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(20)] + [(99, [3.0, 4.0])], "vec_id long, vec array<double>")
    asked = spark.createDataFrame([(50, [0.0, 0.0], 5.0), (51, [3.0, 4.0], 0.0), (52, [0.0, 0.0], 5.000000000001)], "vec_id long, vec array<double>, far double")
    want = {50: 5, 52: 7}  # (5, 0) and (3, 4) lie at 5 exactly; none is nearer than 0
    assert {r["query_id"]: r["n"] for r in E.count_nearer(base, asked).collect()} == want
    monkeypatch.setattr(E, "TASK_PAIRS", 5)
    assert {r["query_id"]: r["n"] for r in E.count_nearer(base, asked).collect()} == want
