import numpy as np
import pyarrow as pa

from vecgraph.sources import vectors as X


def test_raw_float_files(spark, tmp_path):
    x = np.random.default_rng(0).normal(size=(20, 3)).astype("<f4")
    (tmp_path / "a.f32").write_bytes(x.tobytes() + b"\0\0")  # a broken last record is left out
    got = X.from_raw_floats(spark, str(tmp_path), 3).orderBy("vec_id").collect()
    assert len(got) == 20 and np.allclose(sorted(r["vec"][0] for r in got), sorted(x[:, 0].astype(float)))


def test_csv_with_bad_lines(spark, tmp_path):
    (tmp_path / "v.csv").write_text("1,0.5 -1e3\n2,x 1\n")
    got = {r["vec_id"]: r["vec"] for r in X.from_csv(spark, str(tmp_path / "v.csv")).collect()}
    assert got[1] == [0.5, -1000.0] and got[2] == [None, 1.0]


def test_trigrams():
    n = X.trigram_counts(pa.array(["abcABC", "ab", None, "ñañ"]), 256)
    assert n.sum(axis=1).tolist() == [4, 0, 0, 1] and n[0, (97 * 961 + 98 * 31 + 99) % 256] == 2


def test_numeric_vectors_with_a_constant_column(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(1, 1.0, 5.0), (2, 3.0, 5.0)], "id long, a double, b double")
    got = X.numeric_vectors(df, "id", {"a": F.col("a"), "b": F.col("b")}).orderBy("vec_id").collect()
    assert [r["vec"] for r in got] == [[-1.0, 0.0], [1.0, 0.0]]


def test_bucketed_table_joins_without_moving(spark, sf):
    from vecgraph.sources.index_store import bucketed
    from vecgraph.sources.vectors import embedding_vectors

    v = embedding_vectors(spark, sf).select("vec_id", "vec")
    spark.sql("DROP TABLE IF EXISTS bucketed_vectors")
    a = bucketed(v, "bucketed_vectors", 4)
    try:
        assert a.count() == v.count()
        plan = a.join(a.selectExpr("vec_id", "vec AS other").hint("merge"), "vec_id")._jdf.queryExecution().executedPlan().toString()
        assert "Exchange hashpartitioning" not in plan
    finally:
        spark.sql("DROP TABLE bucketed_vectors")
