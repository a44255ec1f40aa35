import numpy as np

from vecgraph.operators import codecs as C
from vecgraph.operators.kernels import Tables
from vecgraph.operators.layout import pack_codes, unpack_codes
from vecgraph.sources.index_store import codec_from_json, codec_to_json
from vecgraph.sources.vectors import embedding_vectors


def frame(spark, x):
    return spark.createDataFrame([(i, [float(y) for y in r]) for i, r in enumerate(x)], "vec_id long, vec array<double>")


def test_quantiser():
    d = np.array([0, 10, 5, 0.0391, 0.0393, 11, -1])
    assert C.quantise(d, 0, 10, 8).tolist() == [0, 255, 127, 0, 1, 255, 0]
    assert C.quantise(d, 0, 0, 8).tolist() == [0] * 7


def test_scalar_limits(spark):
    x = np.random.default_rng(0).normal(size=(50, 5))
    x[:, 2] = 3.0  # a constant dimension
    v = frame(spark, x)
    for bits, tol in ((2, 3.0), (8, 0.02), (16, 1e-4)):
        c = C.ScalarCodec(bits).fit(v)
        codes = c.codes(x)
        assert codes.min() >= 0 and codes.max() <= 2**bits - 1
        assert np.abs(c.decoded(codes) - x).max() < tol and (c.decoded(codes)[:, 2] == 3.0).all()
    assert C.ScalarCodec(4).fit(v).bytes_per_vector() == 5 and C.ScalarCodec(4).fit(v).bytes_per_vector(packed=True) == 2.5


def test_product_lossless_when_centroids_suffice(spark):
    x = np.random.default_rng(1).integers(0, 3, (16, 6)).astype(float)
    c = C.ProductCodec(3, 4, 3, sample=0).fit(frame(spark, x))
    assert np.abs(c.decoded(c.codes(x)) - x).max() < 1e-6


def test_split_and_uneven_subspaces(spark):
    assert C.split_dims(7, 3) == [(0, 3), (3, 5), (5, 7)]
    x = np.random.default_rng(2).normal(size=(60, 7))
    c = C.ProductCodec(3, 3, 2, sample=0).fit(frame(spark, x))
    assert c.codes(x).shape == (60, 3) and c.decoded(c.codes(x)).shape == (60, 7)


def test_principal_axes_keep_distances(spark):
    x = np.random.default_rng(3).normal(size=(80, 6)) @ np.diag([5, 3, 2, 1, 0.1, 0.01])
    v = frame(spark, x)
    c = C.PrincipalCodec(dims=6).fit(v)
    y = c.codes(x)
    assert np.allclose(((y[:40] - y[40:]) ** 2).sum(1), ((x[:40] - x[40:]) ** 2).sum(1))
    assert (np.diff(c.values) <= 1e-9).all() and C.PrincipalCodec(0.9).fit(v).kept < 6
    assert np.allclose(C.PrincipalCodec(dims=6, center=True).fit(v).decoded(C.PrincipalCodec(dims=6, center=True).fit(v).codes(x)), x)


def test_aligned_codes_and_tables_agree(spark, sf):
    v = embedding_vectors(spark, sf)
    c = C.AlignedCodec(16, iters=2, sample=0).fit(v)
    both = c.encode_with_tables(v).orderBy("vec_id").collect()
    x = np.array([r["vec"] for r in both])
    assert (np.array([r["code"] for r in both]) == c.codes(x)).all()
    source = c.source(x)
    # without clamping the sums stay within the bits of an entry
    sums = source.of(source.own(np.arange(50)), np.tile(np.arange(len(x)), (50, 1)))
    assert sums.max() <= 255
    # sums whose true gap exceeds the quantiser's loss never invert
    plain = C.AlignedCodec(16, iters=2, sample=0, table_bits=None)
    plain.__dict__.update({k: w for k, w in c.__dict__.items() if k != "table_bits"})
    true = Tables(source.codes, plain.tables(x).astype(np.float64), c.between, np.float64).of(plain.tables(x)[:20], np.tile(np.arange(200), (20, 1)))
    near = sums[:20, :200].astype(int)
    gap = c.m * c.range / 255
    i, j = np.triu_indices(200, 1)
    for t, s in zip(true, near, strict=True):
        assert not ((t[i] - t[j] >= gap) & (s[i] < s[j])).any()


def test_block_width_changes_nothing(spark, sf):
    v = embedding_vectors(spark, sf)
    c = C.AlignedCodec(16, iters=1, sample=0).fit(v)
    x = np.array([r[0] for r in v.select("vec").limit(60).collect()])
    ids = np.random.default_rng(0).integers(0, 60, (20, 16))
    want = c.source(x).of(c.source(x).own(np.arange(20)), ids)
    for block in (1, 2, 4):
        assert (c.source(x, block=block).of(c.source(x).own(np.arange(20)), ids) == want).all()


def test_packing_round_trip(spark):
    df = spark.createDataFrame([(1, [1, 2, 15, 0]), (2, [7, 8, 9])], "vec_id long, code array<int>")
    got = {r["vec_id"]: r for r in unpack_codes(pack_codes(df)).collect()}
    assert bytes(got[1]["packed"]) == b"\x12\xf0" and list(got[1]["code"]) == [1, 2, 15, 0] and list(got[2]["code"]) == [7, 8, 9, 0]


def test_model_survives_json(spark, sf):
    v = embedding_vectors(spark, sf)
    c = C.AlignedCodec(8, iters=1, sample=0).fit(v)
    again = codec_from_json(codec_to_json(c))
    x = np.array([r[0] for r in v.select("vec").limit(20).collect()])
    assert (again.codes(x) == c.codes(x)).all() and (again.query_state(x) == c.query_state(x)).all()


def test_empty_subspace_of_identical_vectors(spark):
    x = np.ones((5, 4))
    c = C.AlignedCodec(2, iters=1, sample=0, pca=False).fit(frame(spark, x))
    assert np.abs(c.decoded(c.codes(x)) - x).max() < 1e-6
    # with axes: no variance, one axis kept, all distances 0
    c = C.AlignedCodec(2, iters=1, sample=0).fit(frame(spark, x))
    assert (c.source(x).of(c.query_state(x), np.tile(np.arange(5), (5, 1))) == 0).all()


def test_product_picks_the_centroids_of_the_folded_sums(monkeypatch):
    rng = np.random.default_rng(5)
    x, parts = rng.normal(size=(700, 10)), [(0, 5), (5, 10)]
    books = [x[:60, a:b].copy() for a, b in parts]
    for b in books:
        b[30:] = b[:30]  # each centroid twice: ties go to the smaller
    x[600:] = x[:100]
    whole, measured = C.nearest_centroids(x, books, parts)[0], []
    assert (C.nearest_codes(x, books, parts) == whole).all() and (whole < 30).all()
    books = [x[:60, a:b].copy() for a, b in parts]
    whole, before = C.nearest_centroids(x, books, parts)[0], C.nearest_centroids
    monkeypatch.setattr(C, "nearest_centroids", lambda *a: measured.append(len(a[0])) or before(*a))
    assert (C.nearest_codes(x, books, parts) == whole).all() and sum(measured) < 100


def test_larger_samples_sort_one_range_of_hashes(spark, monkeypatch):
    v = spark.range(5000).selectExpr("id * 7919 as vec_id", "array(double(id)) as vec")
    ids = lambda size: {r["vec_id"] for r in C.stable_sample(v, size).collect()}
    sizes = (10, 700, 2500, 5000, 6000)
    whole = [ids(n) for n in sizes]
    monkeypatch.setattr(C, "SORTED_ROWS", 20)
    assert [ids(n) for n in sizes] == whole and [len(x) for x in whole] == [10, 700, 2500, 5000, 5000]
    assert "TakeOrdered" not in C.stable_sample(v, 5000)._jdf.queryExecution().executedPlan().toString()
