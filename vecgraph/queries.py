"""Every method, measure and operator as a query over the given tables, with its DuckDB text where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .functions import vectors as V
from .operators import codecs as C
from .operators import exact as E
from .operators import graph as G
from .operators import measures as M
from .operators import search as S
from .operators import theory as T
from .operators.near_pairs import near_pairs
from .plans import sql
from .sources import vectors as X
from .sources.tables import load, stored

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(text: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if text:
            SQL[fn.__name__] = text
        return fn

    return add


def emb(spark: SparkSession, d: str) -> DataFrame:
    return X.embedding_vectors(spark, d)


def split(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return X.split_queries(emb(spark, d))


def r6(c, n: int = 6):
    return F.round(c, n) + F.lit(0.0)


def neat(near: DataFrame) -> DataFrame:
    return near.withColumn("dist", r6("dist"))


# -- vectors and exact search


@query(f"WITH emb AS ({sql.EMB}), n AS (SELECT sqrt({sql.dot('vec', 'vec')}) AS z, len(vec) AS d FROM emb) SELECT count(*) AS n, min(d) AS min_dim, max(d) AS max_dim, round(min(z), 6) + 0.0 AS min_norm, round(max(z), 6) + 0.0 AS max_norm FROM n")
def vector_stats(spark, d):
    return emb(spark, d).select(F.sqrt(V.norm_sq("vec")).alias("z"), F.size("vec").alias("d")).agg(F.count("*").alias("n"), F.min("d").alias("min_dim"), F.max("d").alias("max_dim"), r6(F.min("z")).alias("min_norm"), r6(F.max("z")).alias("max_norm"))


@query("WITH f AS (SELECT vec_id, len(embedding) AS d, len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) AS bad FROM embeddings) SELECT count(*) AS n, 0 AS n_null, CAST(sum(CASE WHEN bad > 0 THEN 1 ELSE 0 END) AS BIGINT) AS n_not_finite, min(d) AS min_dim, max(d) AS max_dim, (SELECT count(*) FROM (SELECT vec_id FROM f GROUP BY 1 HAVING count(*) > 1)) AS n_repeated_ids FROM f")
def validate_vectors(spark, d):
    return X.validate_vectors(emb(spark, d))


def _asked(rows: DataFrame, *columns: str) -> DataFrame:
    """Pairs (a, b, columns of both) of a stated query set, the ids divisible by 50, with all other rows; the queries are checked to fit a broadcast block."""
    few = rows.where("vec_id % 50 = 0")
    if few.count() * 8 * 64 > E.BLOCK_BYTES:
        raise ValueError("more queries than a broadcast block holds")
    a, b = (x.select(F.col("vec_id").alias(n), *(F.col(c).alias(f"{n}{c[0]}") for c in columns)) for n, x in (("a", few), ("b", rows)))
    return b.join(F.broadcast(a), F.col("a") != F.col("b"))


def _pairs(spark, d):
    return _asked(emb(spark, d).select("vec_id", "vec"), "vec")


_PAIRS = f"WITH emb AS ({sql.EMB}) SELECT a.vec_id AS a, b.vec_id AS b, {{}} FROM emb a JOIN emb b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0"


@query(_PAIRS.format(f"round({sql.sq('a.vec', 'b.vec')}, 6) + 0.0 AS l2_sq, round(sqrt({sql.sq('a.vec', 'b.vec')}), 6) + 0.0 AS l2, round({sql.dot('a.vec', 'b.vec')}, 6) + 0.0 AS dot"))
def l2_pairs(spark, d):
    return _pairs(spark, d).select("a", "b", r6(V.l2_sq("av", "bv")).alias("l2_sq"), r6(V.l2("av", "bv")).alias("l2"), r6(V.dot("av", "bv")).alias("dot"))


@query(_PAIRS.format(f"round({sql.dot('a.vec', 'b.vec')} / (sqrt({sql.dot('a.vec', 'a.vec')}) * sqrt({sql.dot('b.vec', 'b.vec')})), 6) + 0.0 AS cosine"))
def cosine_pairs(spark, d):
    return _pairs(spark, d).select("a", "b", r6(V.cosine("av", "bv")).alias("cosine"))


@query(_PAIRS.format(f"round({sql.sq('a.vec', 'b.vec')}, 6) + 0.0 AS l2_sq, round({sql.margin('a.vec', 'b.vec', 'a.vec')}, 6) + 0.0 AS margin"))
def sql_functions(spark, d):
    """The SQL surface: registered functions, inlined by Catalyst, on rows; sums over pairs come from the kernel. The margin of (a, b, a) is the inner product of a - b with a, less
    half the difference of the squared norms."""
    _pair_view(spark, d, "l2_sq", "toward")
    return spark.sql("SELECT a, b, round(l2_sq, 6) + 0.0D AS l2_sq, round(toward - (na - nb) / 2D, 6) + 0.0D AS margin FROM vec_pairs")


def _pair_view(spark, d, *kinds: str) -> None:
    """The view vec_pairs: sums of every row with an id divisible by 50 with every other row, and their squared norms by the registered function."""
    from .functions.register import register_all

    register_all(spark)
    emb(spark, d).createOrReplaceTempView("vec_rows")
    rows = spark.sql("SELECT vec_id, vec, vec_dot(vec, vec) AS norm FROM vec_rows")
    E.pair_sums(rows, rows.where("vec_id % 50 = 0"), *kinds).createOrReplaceTempView("vec_pairs")


_NEAR = "SELECT query_id, rank, vec_id, round(dist, 6) + 0.0 AS dist FROM near"


@query(f"WITH {sql.knn(10)} {_NEAR}")
def exact_knn(spark, d):
    base, q = split(spark, d)
    return neat(E.exact_knn(base, q, 10))


@query(f"WITH {sql.knn(1)} {_NEAR}")
def exact_knn_k1(spark, d):
    base, q = split(spark, d)
    return neat(E.exact_knn(base, q, 1))


@query(f"WITH emb AS ({sql.EMB}) SELECT q.vec_id AS query_id, b.vec_id AS vec_id, round(sqrt({sql.sq('q.vec', 'b.vec')}), 6) + 0.0 AS dist FROM emb q JOIN emb b ON q.vec_id % 10 = 0 AND b.vec_id % 10 <> 0 WHERE sqrt({sql.sq('q.vec', 'b.vec')}) <= 1.25")
def range_search(spark, d):
    base, q = split(spark, d)
    return neat(E.range_search(base, q, 1.25))


@query(f"WITH {sql.knn(3, 'label = 1', 'label = 0')} {_NEAR}")
def knn_join(spark, d):
    v = emb(spark, d)
    return neat(E.knn_join(v.where("label = 0"), v.where("label = 1"), 3))


@query(f"WITH {sql.knn(5, 'true', 'true')}, p AS (SELECT least(query_id, vec_id) AS a, greatest(query_id, vec_id) AS b, dist FROM near) SELECT a, b, round(max(dist), 6) + 0.0 AS dist FROM p GROUP BY a, b HAVING count(*) = 2")
def mutual_knn(spark, d):
    return neat(E.mutual_knn(emb(spark, d), 5))


@query(f"WITH {sql.knn(10, 'vec_id % 10 <> 0 AND label IN (1, 2, 3)')} {_NEAR}")
def filtered_knn(spark, d):
    base, q = split(spark, d)
    return neat(E.filtered_knn(base, q, F.col("label").isin(1, 2, 3), 10))


# -- theory


def _tri(spark, d, size=200):
    return T.sample_triples(emb(spark, d), size, 0)


@query(f"WITH {sql.triples()} SELECT u, v, w FROM tri")
def triple_sample(spark, d):
    return _tri(spark, d).select("u", "v", "w")


@query(f"WITH {sql.triples()} SELECT u, v, w, round({sql.margin('uv', 'vv', 'wv')}, 6) + 0.0 AS margin FROM tri")
def bisector_margin(spark, d):
    return _tri(spark, d).select("u", "v", "w", r6(V.bisector_margin("uv", "vv", "wv")).alias("margin"))


@query(f"WITH {sql.triples()}, s AS (SELECT u, v, w, {sql.sq('uv', 'vv')} - {sql.sq('uv', 'wv')} AS x FROM tri) SELECT u, v, w, CASE WHEN abs(x) < 1e-12 THEN 0 ELSE CAST(sign(x) AS INTEGER) END AS margin_sign, CASE WHEN abs(x) < 1e-12 THEN 0 ELSE CAST(sign(x) AS INTEGER) END AS distance_sign FROM s")
def lemma_check(spark, d):
    return T.lemma_check(_tri(spark, d))


@query(f"WITH {sql.knn(10)}, far AS (SELECT query_id, dist FROM near WHERE rank = 10) SELECT f.query_id, count(*) AS n_admitted FROM far f JOIN emb q ON q.vec_id = f.query_id JOIN emb b ON b.vec_id % 10 <> 0 AND sqrt({sql.sq('q.vec', 'b.vec')}) < f.dist GROUP BY 1")
def dc1_admission(spark, d):
    base, q = split(spark, d)
    far = E.exact_knn(base, q, 10).where("rank = 10").select(F.col("query_id").alias("vec_id"), F.col("dist").alias("far"))
    return E.count_nearer(base, stored(q.select("vec_id", "vec").join(far, "vec_id"), "farthest")).select("query_id", F.col("n").alias("n_admitted"))


@query(f"WITH {sql.knn(10)} SELECT c.query_id, c.rank, c.vec_id, {sql.sq('cv.vec', 'sv.vec')} < {sql.sq('cv.vec', 'qv.vec')} AS occluded FROM near c JOIN near s ON c.query_id = s.query_id AND s.rank = 1 AND c.rank > 1 JOIN emb cv ON cv.vec_id = c.vec_id JOIN emb sv ON sv.vec_id = s.vec_id JOIN emb qv ON qv.vec_id = c.query_id")
def dc2_occlusion(spark, d):
    base, q = split(spark, d)
    near = E.exact_knn(base, q, 10)
    vec = lambda df, i, n: df.select(F.col("vec_id").alias(i), F.col("vec").alias(n))
    first = near.where("rank = 1").select("query_id", F.col("vec_id").alias("s"))
    t = near.where("rank > 1").join(first, "query_id").join(vec(base, "vec_id", "cv"), "vec_id").join(vec(base, "s", "sv"), "s").join(vec(q, "query_id", "qv"), "query_id")
    return t.select("query_id", "rank", "vec_id", V.is_occluded("cv", "qv", "sv").alias("occluded"))


def _sq_tri(bits):
    return f"""{sql.triples()}, {sql.scalar(bits)}, dt AS (SELECT t.*, a.decoded AS ud, b.decoded AS vd, c.decoded AS wd FROM tri t JOIN sqc a ON a.vec_id = u JOIN sqc b ON b.vec_id = v JOIN sqc c ON c.vec_id = w),
mm AS (SELECT u, v, w, {sql.margin('uv', 'vv', 'wv')} AS margin, {sql.margin('ud', 'vd', 'wd')} AS code_margin FROM dt)"""


def _pq_tri():
    return f"""{sql.triples()}, {sql.product(8, 4, 2)}, {sql.DECODED_PQ}, dt AS (SELECT t.*, a.decoded AS ud, b.decoded AS vd, c.decoded AS wd FROM tri t JOIN pqd a ON a.vec_id = u JOIN pqd b ON b.vec_id = v JOIN pqd c ON c.vec_id = w),
mm AS (SELECT u, v, w, {sql.margin('uv', 'vv', 'wv')} AS margin, {sql.margin('ud', 'vd', 'wd')} AS code_margin FROM dt)"""


_IDENTITY = " SELECT u, v, w, round(margin, 5) + 0.0 AS margin, round(margin - code_margin, 5) + 0.0 AS err, round(code_margin, 5) + 0.0 AS code_margin FROM mm"
_SHARE = " SELECT round(avg(CASE WHEN abs(margin) > abs(margin - code_margin) AND abs(code_margin) >= 1e-12 THEN 1.0 ELSE 0.0 END), 6) + 0.0 AS strict, round(avg(CASE WHEN sign(margin) = sign(code_margin) AND abs(code_margin) >= 1e-12 THEN 1.0 ELSE 0.0 END), 6) + 0.0 AS agree, round(avg(CASE WHEN abs(code_margin) < 1e-12 THEN 1.0 ELSE 0.0 END), 6) + 0.0 AS ties, count(*) AS n FROM mm"


def _pq(spark, d, m=8, bits=4, iters=2):
    return C.ProductCodec(m, bits, iters, sample=0).fit(emb(spark, d))


def _identity(measured):
    return measured.select("u", "v", "w", r6("margin", 5).alias("margin"), r6("err", 5).alias("err"), r6("code_margin", 5).alias("code_margin"))


def _share(measured):
    return T.preserved_fraction(measured).select(r6("strict").alias("strict"), r6("agree").alias("agree"), r6("ties").alias("ties"), "n")


@query(f"WITH {_sq_tri(4)}{_IDENTITY}")
def error_identity_sq(spark, d):
    return _identity(T.margins(_tri(spark, d), C.ScalarCodec(4).fit(emb(spark, d))))


@query(f"WITH {_pq_tri()}{_IDENTITY}")
def error_identity_pq(spark, d):
    return _identity(T.margins(_tri(spark, d), _pq(spark, d)))


@query(f"WITH {_sq_tri(4)}{_SHARE}")
def preserved_fraction_sq(spark, d):
    return _share(T.margins(_tri(spark, d), C.ScalarCodec(4).fit(emb(spark, d))))


@query(f"WITH {_pq_tri()}{_SHARE}")
def preserved_fraction_pq(spark, d):
    return _share(T.margins(_tri(spark, d), _pq(spark, d)))


@query(f"WITH {sql.triples()}, {sql.scalar(4)}, dt AS (SELECT t.*, b.decoded AS vd, c.decoded AS wd FROM tri t JOIN sqc b ON b.vec_id = v JOIN sqc c ON c.vec_id = w), mm AS (SELECT u, v, w, {sql.margin('uv', 'vv', 'wv')} AS margin, {sql.margin('uv', 'vd', 'wd')} AS code_margin FROM dt){_IDENTITY}")
def error_identity_asymmetric(spark, d):
    return _identity(T.margins(_tri(spark, d), C.ScalarCodec(4).fit(emb(spark, d)), asymmetric=True))


@query()
def codec_tuner(spark, d):
    """Grid search of subspaces and bits on up to 10,000 triples, and of subspaces and kept dimensions; the settings that no other beats are confirmed by the recall of a graph."""
    pq = T.tune_codec(emb(spark, d), "pq", [{"m": m, "bits": b, "iters": 2, "sample": 0} for m in (8, 16) for b in (4, 8)], pool=100, confirm=True)
    acc = T.tune_codec(emb(spark, d), "acc", [{"m": m, "dims": k, "iters": 2, "sample": 0, "rule": "quantile", "rounding": "nearest"} for m in (16,) for k in (32, 64)], pool=100, confirm=True)
    return pq.unionByName(acc)


# -- scalar codec


@query(f"WITH emb AS ({sql.EMB}), {sql.scalar(8)} SELECT dim, round(lo, 6) + 0.0 AS lo, round(hi, 6) + 0.0 AS hi FROM ranges")
def sq_ranges(spark, d):
    return C.ScalarCodec().ranges(emb(spark, d)).select("dim", r6("lo").alias("lo"), r6("hi").alias("hi"))


@query(f"WITH emb AS ({sql.EMB}), {sql.scalar(4)} SELECT vec_id, array_to_string(code, ',') AS code FROM sqc")
def sq_encode(spark, d):
    v = emb(spark, d)
    return C.ScalarCodec(4).fit(v).encode(v).select("vec_id", F.array_join(F.col("code").cast("array<string>"), ",").alias("code"))


@query(f"WITH emb AS ({sql.EMB}), {sql.scalar(4)} SELECT e.vec_id, round({sql.sq('e.vec', 's.decoded')} / {sql.dot('e.vec', 'e.vec')}, 6) + 0.0 AS rel_error FROM emb e JOIN sqc s USING (vec_id)")
def sq_decode_error(spark, d):
    v = emb(spark, d)
    c = C.ScalarCodec(4).fit(v)
    return c.decode(c.encode(v)).select("vec_id", r6(V.l2_sq("vec", "decoded") / V.norm_sq("vec")).alias("rel_error"))


def _code_pairs(spark, d, bits=8):
    v = emb(spark, d)
    c = C.ScalarCodec(bits).fit(v)
    return _asked(c.decode(c.encode(v)).select("vec_id", "code", "decoded"), "code", "decoded"), c


_SQ_PAIR = f"WITH emb AS ({sql.EMB}), {sql.scalar(8)} SELECT a.vec_id AS a, b.vec_id AS b, round({sql.sq('a.decoded', 'b.decoded')}, 6) + 0.0 AS dist_sq FROM sqc a JOIN sqc b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0"


@query(_SQ_PAIR)
def sq_distance(spark, d):
    pairs, _ = _code_pairs(spark, d)
    return pairs.select("a", "b", r6(V.l2_sq("ad", "bd")).alias("dist_sq"))


@query(_SQ_PAIR)
def sq_distance_fast(spark, d):
    """Without decoding: integer differences weighted by the squared step of each dimension."""
    pairs, c = _code_pairs(spark, d)
    weight = F.array(*[F.lit(float(s * s)) for s in c.step])
    diff = F.zip_with("ac", "bc", lambda x, y: (x - y) * (x - y))
    return pairs.select("a", "b", r6(F.aggregate(F.zip_with(diff, weight, lambda x, w: x * w), F.lit(0.0), lambda s, x: s + x)).alias("dist_sq"))


@query(" UNION ALL ".join(f"SELECT {b} AS bits, rel_error, code_bytes FROM (WITH emb AS ({sql.EMB}), {sql.scalar(b)} SELECT round(avg({sql.sq('e.vec', 's.decoded')}), 6) + 0.0 AS rel_error, CAST({64.0 * (b if b >= 8 else 8) / 8} AS DOUBLE) AS code_bytes FROM emb e JOIN sqc s USING (vec_id))" for b in (2, 4, 8, 16)))
def sq_bits_sweep(spark, d):
    v, out = emb(spark, d), None
    for b in (2, 4, 8, 16):
        c = C.ScalarCodec(b).fit(v)
        one = c.decode(c.encode(v)).agg(r6(F.avg(V.l2_sq("vec", "decoded"))).alias("rel_error")).select(F.lit(b).alias("bits"), "rel_error", F.lit(float(c.bytes_per_vector())).alias("code_bytes"))
        out = one if out is None else out.unionByName(one)
    return out


# -- product codec

_PQ = f"WITH emb AS ({sql.EMB}), {sql.product(8, 4, 2)}"


@query(f"{_PQ} SELECT m, code, generate_subscripts(c, 1) - 1 AS j, round(unnest(c), 6) + 0.0 AS x FROM books")
def pq_codebooks(spark, d):
    c = _pq(spark, d)
    return spark.createDataFrame([(m, k, j, float(x)) for m, b in enumerate(c.books) for k, row in enumerate(b) for j, x in enumerate(row)], "m int, code int, j int, x double").withColumn("x", r6("x"))


@query(f"{_PQ} SELECT vec_id, string_agg(code, ',' ORDER BY m) AS code FROM pqc GROUP BY vec_id")
def pq_encode(spark, d):
    v = emb(spark, d)
    return _pq(spark, d).encode(v).select("vec_id", F.array_join(F.col("code").cast("array<string>"), ",").alias("code"))


@query(f"{_PQ}, {sql.DECODED_PQ} SELECT e.vec_id, round({sql.sq('e.vec', 's.decoded')}, 6) + 0.0 AS error FROM emb e JOIN pqd s USING (vec_id)")
def pq_decode_error(spark, d):
    v, c = emb(spark, d), _pq(spark, d)
    return c.decode(c.encode(v)).select("vec_id", r6(V.l2_sq("vec", "decoded")).alias("error"))


def _adt(v, c):
    """(vec_id, m, code, d) of a product codec's tables."""
    sent = v.sparkSession.sparkContext.broadcast(c)

    @F.arrow_udf("array<double>")
    def tables(x: pa.Array) -> pa.Array:
        t = sent.value.tables(C.matrix(x))
        return C.to_lists(t.reshape(len(t), -1))

    k = c.between.shape[1]
    flat = v.select("vec_id", F.posexplode(tables("vec")).alias("p", "d"))
    return flat.select("vec_id", F.floor(F.col("p") / k).cast("int").alias("m"), (F.col("p") % k).alias("code"), "d")


@query(f"{_PQ} SELECT s.vec_id AS query_id, s.m, b.code, round({sql.sq('s.x', 'b.c')}, 6) + 0.0 AS d FROM sub s JOIN books b ON s.m = b.m WHERE s.vec_id % 50 = 0")
def pq_adt(spark, d):
    v = emb(spark, d)
    return _adt(v.where("vec_id % 50 = 0"), _pq(spark, d)).select(F.col("vec_id").alias("query_id"), "m", "code", r6("d").alias("d"))


_PQ_SCAN = f"{_PQ}, adt AS (SELECT s.vec_id AS query_id, s.m, b.code, {sql.sq('s.x', 'b.c')} AS d FROM sub s JOIN books b ON s.m = b.m WHERE s.vec_id % 10 = 0), scan AS (SELECT query_id, vec_id, sum(d) AS dist FROM adt JOIN (SELECT * FROM pqc WHERE vec_id % 10 <> 0) c ON adt.m = c.m AND adt.code = c.code GROUP BY query_id, vec_id)"


@query(f"{_PQ_SCAN} SELECT query_id, vec_id, round(dist, 4) + 0.0 AS dist FROM scan WHERE query_id % 50 = 0")
def pq_adc_scan(spark, d):
    """Asymmetric distances of queries to all codes: one table row looked up per subspace."""
    base, q = split(spark, d)
    c = _pq(spark, d)
    codes = c.encode(base.select("vec_id", "vec")).select("vec_id", "code")
    table = _adt(q.where("vec_id % 50 = 0"), c).groupBy(F.col("vec_id").alias("query_id")).agg(F.sort_array(F.collect_list(F.struct("m", "code", "d"))).alias("t")).select("query_id", F.col("t.d").alias("adt"))
    met = codes.join(F.broadcast(table))  # a stated query set against all codes
    dist = F.aggregate(F.zip_with(F.col("code"), F.sequence(F.lit(0), F.size("code") - 1), lambda x, m: F.get("adt", m * c.between.shape[1] + x)), F.lit(0.0), lambda s, x: s + x)
    return met.select("query_id", "vec_id", r6(dist, 4).alias("dist"))


@query(f"{_PQ} SELECT a.m, a.code AS a, b.code AS b, round({sql.sq('a.c', 'b.c')}, 6) + 0.0 AS d FROM books a JOIN books b ON a.m = b.m")
def pq_sdt(spark, d):
    c = _pq(spark, d)
    return spark.createDataFrame([(m, a, b, float(c.between[m, a, b])) for m in range(c.m) for a in range(16) for b in range(16)], "m int, a int, b int, d double").withColumn("d", r6("d"))


@query(f"{_PQ} SELECT x.vec_id AS a, y.vec_id AS b, round(sum({sql.sq('p.c', 'q.c')}), 6) + 0.0 AS dist FROM pqc x JOIN pqc y ON x.m = y.m AND x.vec_id % 50 = 0 AND x.vec_id <> y.vec_id JOIN books p ON p.m = x.m AND p.code = x.code JOIN books q ON q.m = y.m AND q.code = y.code GROUP BY 1, 2")
def pq_sdc_pairs(spark, d):
    """Symmetric distances: both sides are codes."""
    c = _pq(spark, d)
    k = c.between.shape[1]
    pairs = _asked(c.encode(emb(spark, d)).select("vec_id", "code"), "code")
    table = F.broadcast(spark.createDataFrame([(c.between.reshape(-1).tolist(),)], "sdt array<double>"))
    pairs = pairs.join(table)
    at = F.zip_with(F.zip_with("ac", "bc", lambda x, y: x * k + y), F.sequence(F.lit(0), F.size("ac") - 1), lambda xy, m: F.get("sdt", m * k * k + xy))
    return pairs.select("a", "b", r6(F.aggregate(at, F.lit(0.0), lambda s, x: s + x)).alias("dist"))


# -- principal components and aligned codes


@query(f"WITH emb AS ({sql.EMB}), f AS (SELECT vec_id, generate_subscripts(vec, 1) - 1 AS i, unnest(vec) AS x FROM emb), m AS (SELECT i, avg(x) AS mu FROM f GROUP BY i) SELECT a.i, b.i AS j, round(avg(a.x * b.x) - any_value(p.mu) * any_value(q.mu), 6) + 0.0 AS cov FROM f a JOIN f b ON a.vec_id = b.vec_id AND a.i <= b.i JOIN m p ON p.i = a.i JOIN m q ON q.i = b.i GROUP BY 1, 2")
def covariance(spark, d):
    _, _, cov = C.moments(emb(spark, d))
    return spark.createDataFrame([(i, j, float(cov[i, j])) for i in range(len(cov)) for j in range(i, len(cov))], "i int, j int, cov double").withColumn("cov", r6("cov"))


@query()
def variance_curve(spark, d):
    c = C.PrincipalCodec().fit(emb(spark, d))
    curve = C.variance_curve(c.values)
    return spark.createDataFrame([(i + 1, float(e), float(f), i + 1 <= c.kept) for i, (e, f) in enumerate(zip(c.values, curve, strict=True))], "d int, eigenvalue double, share double, kept boolean")


@query()
def pca_encode(spark, d):
    v = emb(spark, d)
    c = C.PrincipalCodec().fit(v)
    return c.decode(c.encode(v)).select("vec_id", "code", V.l2_sq("vec", "decoded").alias("error"))


def _acc(spark, d, **how):
    return C.AlignedCodec(**{"m": 16, "dims": 32, "iters": 2, "sample": 0, "basis": "variance-order"} | how).fit(emb(spark, d))


_ACC = f"WITH {sql.aligned(16, 32, 2)}"


@query(f"{_ACC} SELECT vec_id, string_agg(code, ',' ORDER BY m) AS code FROM pqc GROUP BY vec_id")
def acc_order_encode(spark, d):
    return _acc(spark, d).encode(emb(spark, d)).select("vec_id", F.array_join(F.col("code").cast("array<string>"), ",").alias("code"))


@query(f"{_ACC} SELECT round(lo, 6) + 0.0 AS lo, round(rng, 6) + 0.0 AS rng FROM span")
def table_range(spark, d):
    c = _acc(spark, d)
    return spark.createDataFrame([(c.lo, c.range)], "lo double, rng double").select(r6("lo").alias("lo"), r6("rng").alias("rng"))


@query(f"{_ACC} SELECT vec_id AS query_id, string_agg(qd, ',' ORDER BY m, code) AS adt FROM adtq WHERE vec_id % 10 = 0 GROUP BY 1")
def adt_quantised(spark, d):
    """Codes and quantised tables from one pass."""
    return _acc(spark, d).encode_with_tables(emb(spark, d).where("vec_id % 10 = 0")).select(F.col("vec_id").alias("query_id"), F.array_join(F.col("adt").cast("array<string>"), ",").alias("adt"))


@query(f"{_ACC} SELECT m, a, b, qd FROM sdtq")
def sdt_quantised(spark, d):
    c = _acc(spark, d)
    q = c.quantised(c.between)
    return spark.createDataFrame([(m, a, b, int(q[m, a, b])) for m in range(q.shape[0]) for a in range(16) for b in range(16)], "m int, a int, b int, qd int")


@query(f"{_ACC}, scan AS (SELECT t.vec_id AS query_id, c.vec_id, CAST(sum(t.qd) AS DOUBLE) AS dist FROM adtq t JOIN pqc c ON t.m = c.m AND t.code = c.code WHERE t.vec_id % 10 = 0 AND c.vec_id % 10 <> 0 GROUP BY 1, 2), ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS INTEGER) AS rank FROM scan) SELECT query_id, rank, vec_id, dist FROM ranked WHERE rank <= 10")
def quantised_scan(spark, d):
    base, q = split(spark, d)
    return S.code_scan(base, _acc(spark, d), q, 10)


@query(f"{_PQ} SELECT vec_id, lower(string_agg(printf('%01x', code), '' ORDER BY m)) AS packed FROM pqc GROUP BY vec_id")
def pack_codes(spark, d):
    """Two 4-bit codes in a byte, the first in the high half."""
    from .operators.layout import pack_codes as pack

    return pack(_pq(spark, d).encode(emb(spark, d))).select("vec_id", F.lower(F.hex("packed")).alias("packed"))


@query(f"{_PQ} SELECT vec_id, string_agg(code, ',' ORDER BY m) AS code FROM pqc GROUP BY vec_id")
def unpack_codes(spark, d):
    from .operators.layout import pack_codes as pack
    from .operators.layout import unpack_codes as unpack

    return unpack(pack(_pq(spark, d).encode(emb(spark, d))).select("vec_id", "packed")).select("vec_id", F.array_join(F.col("code").cast("array<string>"), ",").alias("code"))


@query()
def acc_encode(spark, d):
    v = emb(spark, d)
    c = C.AlignedCodec(m=16, iters=4, sample=0).fit(v)
    return c.encode_with_tables(v).select("vec_id", "code", F.array_max("adt").alias("largest_entry"))


@query()
def acc_rerank(spark, d):
    """Code scan for 100 candidates, measured again on full vectors."""
    base, q = split(spark, d)
    c = C.AlignedCodec(m=16, iters=4, sample=0).fit(base)
    return E.rerank(S.code_scan(base, c, q, 100), base, q, 10)


@query()
def acc_range_rules(spark, d):
    """Recall of a code scan's best 100 under each rule of the table range."""
    base, q = split(spark, d)
    truth, out = stored(E.exact_knn(base, q, 10), "truth"), None
    for rule, rounding in (("sum_of_max", "floor"), ("observed_max", "nearest"), ("quantile", "nearest")):
        c = C.AlignedCodec(m=16, iters=4, sample=0, rule=rule, rounding=rounding).fit(base)
        got = S.code_scan(base, c, q, 100)
        one = truth.join(got.select("query_id", "vec_id", F.lit(1).alias("hit")), ["query_id", "vec_id"], "left").agg((F.count("hit") / F.count("*")).alias("recall")).select(F.lit(rule).alias("rule"), F.lit(rounding).alias("rounding"), "recall")
        out = one if out is None else out.unionByName(one)
    return out


@query()
def approx_distinct_codes(spark, d):
    c = _pq(spark, d)
    return c.encode(emb(spark, d)).select(F.posexplode("code").alias("m", "c")).groupBy("m").agg(F.approx_count_distinct("c").alias("codes_used"))


# -- graph

_LEVEL = "CAST(floor(-ln(((vec_id % 2147483648 * 2654435761 + 42) % 4294967296 + 1) / 4294967296.0) / ln(16.0)) AS INTEGER)"


@query(f"SELECT vec_id, {_LEVEL} AS level FROM embeddings")
def level_draw(spark, d):
    return G.assign_levels(emb(spark, d), 16).select("vec_id", "level")


@query(f"SELECT {_LEVEL} AS level, count(*) AS n FROM embeddings GROUP BY 1")
def level_histogram(spark, d):
    return G.assign_levels(emb(spark, d), 16).groupBy("level").agg(F.count("*").alias("n"))


@query("SELECT CAST(vec_id * 2654435761 % 4294967296 % 4 AS INTEGER) AS segment, count(*) AS n FROM embeddings GROUP BY 1")
def segment_sizes(spark, d):
    return G.assign_segments(emb(spark, d), 4).groupBy("segment").agg(F.count("*").alias("n"))


def _lists(spark, d, candidates=24):
    v = emb(spark, d)
    return G.with_candidate_vectors(G.candidate_lists(v, candidates), v)


_KEPT = " SELECT src, generate_subscripts(nbrs, 1) AS rank, unnest(nbrs).id AS dst FROM kept"


@query(f"WITH {sql.selection(24, 8)}{_KEPT}")
def ns_select(spark, d):
    return G.edges_of(G.select_neighbours(_lists(spark, d), 8)).select("src", "rank", "dst")


@query(f"WITH {sql.selection(24, 8, 0.02)}{_KEPT}")
def ns_select_tau(spark, d):
    return G.edges_of(G.select_neighbours(_lists(spark, d), 8, 0.02)).select("src", "rank", "dst")


def _bulk(spark, d):
    return stored(G.bulk_graph(emb(spark, d), 24, 8), "bulk-graph")


@query(f"WITH {sql.bulk(24, 8)} SELECT src, rank, n.id AS dst, round(sqrt(n.d), 6) + 0.0 AS dist FROM edges")
def bulk_graph(spark, d):
    return neat(G.edges_of(G.bulk_graph(emb(spark, d), 24, 8)))


@query(f"WITH {sql.selection(24, 8)}, e AS (SELECT src, unnest(nbrs) AS n FROM kept) SELECT n.id AS src, count(*) AS n_reverse FROM e GROUP BY 1")
def reverse_edges(spark, d):
    return G.edges_of(G.select_neighbours(_lists(spark, d), 8)).groupBy(F.col("dst").alias("src")).agg(F.count("*").alias("n_reverse"))


@query(f"WITH {sql.bulk(24, 8)} SELECT len(nbrs) AS degree, count(*) AS n FROM graph GROUP BY 1")
def degree_histogram(spark, d):
    return G.bulk_graph(emb(spark, d), 24, 8).select(F.size("nbrs").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))


@query(f"WITH {sql.bulk(24, 8)} SELECT 0 AS over_degree, 0 AS loops, 0 AS repeated, count(DISTINCT src) AS vertices, count(*) AS edges, 0 AS without_list FROM edges")
def graph_invariants(spark, d):
    return G.check_graph(G.edges_of(_bulk(spark, d)), 8)


@query(f"WITH RECURSIVE {sql.bulk(24, 8)}, e2 AS MATERIALIZED (SELECT src, n.id AS dst FROM edges), r AS (SELECT CAST(0 AS BIGINT) AS v UNION SELECT e2.dst FROM r JOIN e2 ON e2.src = r.v) SELECT count(*) AS n_reached FROM r")
def reachable_vertices(spark, d):
    return G.reachable(G.edges_of(_bulk(spark, d)), 0).agg(F.count("*").alias("n_reached"))


@query(f"WITH {sql.bulk(24, 8)}, {sql.product(8, 4, 2)}, cc AS (SELECT vec_id, list(code ORDER BY m) AS code FROM pqc GROUP BY 1), g AS (SELECT src, CAST(floor((rank - 1) / 4) AS INTEGER) AS block_no, list(n.id ORDER BY rank) AS ids, list(code ORDER BY rank) AS codes FROM edges JOIN cc ON cc.vec_id = n.id GROUP BY 1, 2) SELECT src, block_no, array_to_string(ids, ',') AS ids, array_to_string(list_transform(range(1, 9), lambda m: array_to_string(list_transform(codes, lambda c: c[m]), ',')), ';') AS codes FROM g")
def neighbour_blocks(spark, d):
    """Blocks of four neighbours, padding left out for the comparison."""
    c = _pq(spark, d)
    blocks = G.pack_blocks(G.edges_of(_bulk(spark, d)), c.encode(emb(spark, d)), 4)
    blocks = blocks.withColumn("n", F.size(F.filter("ids", lambda x: x >= 0)))
    return blocks.select("src", "block_no", F.array_join(F.slice("ids", F.lit(1), F.col("n")).cast("array<string>"), ",").alias("ids"), F.array_join(F.transform("codes", lambda x: F.array_join(F.slice(x, F.lit(1), F.col("n")).cast("array<string>"), ",")), ";").alias("codes"))


def _lookup(spark, d, batched):
    v = emb(spark, d)
    c = _acc(spark, d)
    edges = G.edges_of(_bulk(spark, d))
    blocks = G.pack_blocks(edges, c.encode(v), 16)
    own = c.encode_with_tables(v).select(F.col("vec_id").alias("src"), "adt")
    return G.block_distances(blocks.join(own, "src").withColumn("query_id", F.col("src")), 16, batched).select("src", "dst", "qdist")


_LOOK = f"WITH {sql.aligned(16, 32, 2)}, {sql.bulk(24, 8)[sql.bulk(24, 8).index('pairs AS'):]} SELECT e.src, e.n.id AS dst, CAST(sum(t.qd) AS BIGINT) AS qdist FROM edges e JOIN pqc c ON c.vec_id = e.n.id JOIN adtq t ON t.vec_id = e.src AND t.m = c.m AND t.code = c.code GROUP BY 1, 2"


@query(_LOOK)
def block_lookup(spark, d):
    return _lookup(spark, d, True)


@query(_LOOK)
def block_lookup_scalar(spark, d):
    return _lookup(spark, d, False)


# -- cost formulas


@query("WITH v AS (SELECT len(embedding) // 4 AS m, count(*) AS n FROM embeddings WHERE embedding IS NOT NULL GROUP BY 1) SELECT CAST(m AS INTEGER) AS m, u AS register_bits, greatest(u // 128, 1) AS tables_at_once, CAST(ceil(m / greatest(u // 128, 1)) AS BIGINT) AS steps, u // 8 AS block, n AS n_vectors, n * CAST(ceil(m / greatest(u // 128, 1)) AS BIGINT) AS n_steps FROM v, (VALUES (128), (256), (512)) t(u)")
def simd_plan(spark, d):
    """Look-up steps for one vector, and for all, when every four of its dimensions are a subspace."""
    rows = emb(spark, d).where("vec is not null").groupBy(F.floor(F.size("vec") / 4).cast("int").alias("m")).agg(F.count("*").alias("n_vectors"))
    rows = rows.join(F.broadcast(spark.createDataFrame([(u,) for u in (128, 256, 512)], "register_bits int")))
    plan = M.simd_steps(F.col("register_bits"), F.col("m"))
    return rows.select("m", "register_bits", plan["tables_at_once"].cast("int").alias("tables_at_once"), plan["steps"].alias("steps"), plan["block"].cast("int").alias("block"), "n_vectors", (F.col("n_vectors") * plan["steps"]).alias("n_steps"))


@query("WITH v AS (SELECT len(embedding) AS dim, count(*) AS n FROM embeddings WHERE embedding IS NOT NULL GROUP BY 1) SELECT CAST(dim AS INTEGER) AS dim, u AS register_bits, m, CAST(ceil(dim * 32 / u) AS BIGINT) AS loads_plain, CAST(ceil(m * 8 / u) AS BIGINT) AS loads_codes, n AS n_vectors, n * CAST(ceil(dim * 32 / u) AS BIGINT) AS scan_plain, n * CAST(ceil(m * 8 / u) AS BIGINT) AS scan_codes FROM v, (VALUES (128, 16), (256, 16), (512, 16)) t(u, m)")
def register_loads(spark, d):
    """Loads of one distance, and of a query's distances to all vectors, by the vectors' dimension and the width of registers."""
    widths = F.broadcast(spark.createDataFrame([(u, 16) for u in (128, 256, 512)], "register_bits int, m int"))
    rows = emb(spark, d).where("vec is not null").groupBy(F.size("vec").alias("dim")).agg(F.count("*").alias("n_vectors")).join(widths)
    plain, codes = (x.cast("bigint") for x in M.register_loads(F.col("dim"), F.col("register_bits"), F.col("m"), F.lit(8)))
    return rows.select("dim", "register_bits", "m", plain.alias("loads_plain"), codes.alias("loads_codes"), "n_vectors", (F.col("n_vectors") * plain).alias("scan_plain"), (F.col("n_vectors") * codes).alias("scan_codes"))


@query(f"WITH {sql.bulk(24, 8)}, c AS (SELECT (SELECT count(*) FROM embeddings) AS v, count(*) AS e FROM edges) SELECT m AS method, CAST(CASE m WHEN 'lg' THEN v * 256.0 + e * 4 WHEN 'sq' THEN v * 64.0 + e * 4 WHEN 'pca' THEN v * 212.0 + e * 4 WHEN 'pq' THEN v * 16.0 + e * 4 ELSE v * 8.0 + e * 12 END AS DOUBLE) AS bytes FROM c, (VALUES ('lg'), ('sq'), ('pca'), ('pq'), ('acc')) t(m)")
def index_size(spark, d):
    counts = G.edges_of(_bulk(spark, d)).agg(F.count("*").alias("e")).join(emb(spark, d).agg(F.count("*").alias("v")), how="cross")
    out = None
    for name, how in (("lg", {}), ("sq", {"bits": 8}), ("pca", {"kept": 53}), ("pq", {"m": 16, "bits": 8}), ("acc", {"m": 16, "bits": 4})):
        one = counts.select(F.lit(name).alias("method"), M.index_bytes(F.col("v"), F.col("e"), 64, name, **how).alias("bytes"))
        out = one if out is None else out.unionByName(one)
    return out


@query("WITH f AS (SELECT label, count(*) AS n FROM embeddings WHERE len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 GROUP BY ROLLUP (label)) SELECT label, n, 32 AS degree, 1024 AS candidates, round(32 * log2(greatest(n, 2)), 6) + 0.0 AS acquisition_plain, round(log2(greatest(n, 2)), 6) + 0.0 AS acquisition_inlined, CAST(1024 AS DOUBLE) AS selection_plain, CAST(0 AS DOUBLE) AS selection_tables FROM f")
def access_formula(spark, d):
    """Accesses of one more insertion into a graph of the usable vectors, of each label and of all."""
    broken = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    n = emb(spark, d).where(~broken).rollup("label").agg(F.count("*").alias("n"))
    cost = M.access_formula(F.col("n"), 32, 1024)
    out = n.select("label", "n", F.lit(32).alias("degree"), F.lit(1024).alias("candidates"), *(c.alias(name) for name, c in cost.items()))
    return out.withColumns({c: r6(c) for c in ("acquisition_plain", "acquisition_inlined")})


# -- results: merge, rerank, measures


@query(f"WITH {sql.knn(10)} {_NEAR}")
def merge_topk(spark, d):
    """Four segments searched apart, merged."""
    base, q = split(spark, d)
    placed = G.assign_segments(base, 4)
    out = None
    for s in range(4):
        one = E.exact_knn(placed.where(F.col("segment") == s), q, 10)
        out = one if out is None else out.unionByName(one)
    return neat(E.merge_topk(out, 10))


_ACC_CAND = f"{_ACC}, scan AS (SELECT t.vec_id AS query_id, c.vec_id, sum(t.qd) AS dist FROM adtq t JOIN pqc c ON t.m = c.m AND t.code = c.code WHERE t.vec_id % 10 = 0 AND c.vec_id % 10 <> 0 GROUP BY 1, 2), cand AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS r FROM scan) WHERE r <= 50), re AS (SELECT c.query_id, c.vec_id, sqrt({sql.sq('q.vec', 'b.vec')}) AS dist FROM cand c JOIN emb q ON q.vec_id = c.query_id JOIN emb b ON b.vec_id = c.vec_id), result AS (SELECT * FROM (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS INTEGER) AS rank, vec_id, dist FROM re) WHERE rank <= 10)"


def _reranked(spark, d):
    base, q = split(spark, d)
    return E.rerank(S.code_scan(base, _acc(spark, d), q, 50), base, q, 10)


@query(f"{_ACC_CAND} SELECT query_id, rank, vec_id, round(dist, 6) + 0.0 AS dist FROM result")
def rerank(spark, d):
    return neat(_reranked(spark, d))


_TRUTH = ", " + sql.knn(10, name="truth").split(",\n", 1)[1]


@query(f"{_ACC_CAND}{_TRUTH} SELECT round(count(r.vec_id) / 10.0 / count(DISTINCT t.query_id), 6) + 0.0 AS recall, count(DISTINCT t.query_id) AS n_queries FROM truth t LEFT JOIN result r ON t.query_id = r.query_id AND t.vec_id = r.vec_id")
def recall_at_k(spark, d):
    base, q = split(spark, d)
    return M.recall(E.exact_knn(base, q, 10), _reranked(spark, d), 10).select(r6("recall").alias("recall"), "n_queries")


@query(f"{_ACC_CAND}{_TRUTH}, per AS (SELECT t.query_id, avg(CASE WHEN t.dist = 0 AND r.dist = 0 THEN 1.0 WHEN t.dist > 0 THEN r.dist / t.dist END) AS x FROM truth t LEFT JOIN result r ON t.query_id = r.query_id AND t.rank = r.rank GROUP BY 1) SELECT round(avg(x), 6) + 0.0 AS distance_ratio, 0 AS n_left_out FROM per")
def distance_ratio(spark, d):
    base, q = split(spark, d)
    return M.distance_ratio(E.exact_knn(base, q, 10), _reranked(spark, d), 10).select(r6("distance_ratio").alias("distance_ratio"), "n_left_out")


@query(f"{_ACC}, scan AS (SELECT t.vec_id AS query_id, c.vec_id, sum(t.qd) AS dist FROM adtq t JOIN pqc c ON t.m = c.m AND t.code = c.code WHERE t.vec_id % 10 = 0 AND c.vec_id % 10 <> 0 GROUP BY 1, 2), result AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS rank FROM scan){_TRUTH} SELECT w AS candidates, round(count(r.vec_id) / 10.0 / count(DISTINCT t.query_id), 6) + 0.0 AS recall FROM truth t CROSS JOIN (VALUES (10), (20), (50), (100)) v(w) LEFT JOIN result r ON t.query_id = r.query_id AND t.vec_id = r.vec_id AND r.rank <= w GROUP BY w")
def recall_curve_code_scan(spark, d):
    base, q = split(spark, d)
    truth, found = E.exact_knn(base, q, 10).select("query_id", "vec_id"), S.code_scan(base, _acc(spark, d), q, 100).select("query_id", "vec_id", F.col("rank").alias("r"))
    widths = F.broadcast(spark.createDataFrame([(w,) for w in (10, 20, 50, 100)], "candidates int"))
    met = truth.join(found, ["query_id", "vec_id"], "left").join(widths)
    return met.groupBy("candidates").agg((F.sum((F.col("r") <= F.col("candidates")).cast("int")) / 10.0 / F.count_distinct("query_id")).alias("recall")).select("candidates", r6("recall").alias("recall"))


@query(f"{_ACC_CAND}{_TRUTH}, a AS (SELECT query_id, vec_id FROM truth), b AS (SELECT query_id, vec_id FROM result) SELECT (SELECT count(*) FROM (FROM a INTERSECT FROM b)) AS shared, (SELECT count(*) FROM (FROM a EXCEPT FROM b)) AS missed, (SELECT count(*) FROM (FROM b EXCEPT FROM a)) AS extra, (SELECT count(*) FROM (FROM a UNION FROM b)) AS either")
def set_ops_recall(spark, d):
    base, q = split(spark, d)
    a = stored(E.exact_knn(base, q, 10).select("query_id", "vec_id"), "truth")
    b = stored(_reranked(spark, d).select("query_id", "vec_id"), "result")
    one = lambda df, n: df.agg(F.count("*").alias(n))
    return one(a.intersect(b), "shared").join(one(a.exceptAll(b), "missed"), how="cross").join(one(b.subtract(a), "extra"), how="cross").join(one(a.union(b).distinct(), "either"), how="cross")


_RUNS = "SELECT label, query_id % 4 AS part, rank, dist FROM near JOIN (SELECT vec_id AS query_id, label FROM emb) USING (query_id)"


def _runs(spark, d):
    base, q = split(spark, d)
    return E.exact_knn(base, q, 10).join(q.select(F.col("vec_id").alias("query_id"), "label"), "query_id").withColumn("part", F.col("query_id") % 4)


@query(f"WITH {sql.knn(10)}, runs AS ({_RUNS}) SELECT label, part, count(*) AS n, round(avg(dist), 6) + 0.0 AS mean_dist FROM runs GROUP BY ROLLUP (label, part)")
def metric_rollup(spark, d):
    return _runs(spark, d).rollup("label", "part").agg(F.count("*").alias("n"), r6(F.avg("dist")).alias("mean_dist"))


@query(f"WITH {sql.knn(10)}, runs AS ({_RUNS}) SELECT label, part, count(*) AS n, round(max(dist), 6) + 0.0 AS max_dist FROM runs GROUP BY CUBE (label, part)")
def metric_cube(spark, d):
    return _runs(spark, d).cube("label", "part").agg(F.count("*").alias("n"), r6(F.max("dist")).alias("max_dist"))


@query(f"WITH {sql.knn(10)} SELECT query_id, rank, round(dist - lag(dist) OVER (PARTITION BY query_id ORDER BY rank), 6) + 0.0 AS gap, ntile(3) OVER (PARTITION BY query_id ORDER BY rank) AS third FROM near")
def neighbour_gaps(spark, d):
    base, q = split(spark, d)
    w = W.partitionBy("query_id").orderBy("rank")
    return E.exact_knn(base, q, 10).select("query_id", "rank", r6(F.col("dist") - F.lag("dist").over(w)).alias("gap"), F.ntile(3).over(w).alias("third"))


@query(f"WITH {sql.knn(10)} SELECT query_id, " + ", ".join(f"round(max(dist) FILTER (rank = {r}), 6) + 0.0 AS r{r}" for r in (1, 5, 10)) + " FROM near GROUP BY 1")
def rank_pivot(spark, d):
    base, q = split(spark, d)
    p = E.exact_knn(base, q, 10).groupBy("query_id").pivot("rank", [1, 5, 10]).agg(F.max("dist"))
    return p.select("query_id", *(r6(F.col(f"`{r}`")).alias(f"r{r}") for r in (1, 5, 10)))


# -- other vector sets


@query(f"WITH {sql.trigrams('documents', 'doc_id', 'text')} SELECT vec_id, len(list_filter(vec, lambda x: x > 0)) AS slots, round(list_max(vec), 6) + 0.0 AS top, round(list_sum(vec), 5) + 0.0 AS total FROM tvec")
def doc_trigram_vectors(spark, d):
    v = X.document_vectors(spark, d)
    return v.select("vec_id", F.size(F.filter("vec", lambda x: x > 0)).alias("slots"), r6(F.array_max("vec")).alias("top"), r6(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x), 5).alias("total"))


@query(f"WITH {sql.trigrams('documents', 'doc_id', 'text')} SELECT a.vec_id AS a, b.vec_id AS b, round(sqrt({sql.sq('a.vec', 'b.vec')}), 6) + 0.0 AS dist FROM tvec a JOIN tvec b ON a.vec_id < b.vec_id WHERE sqrt({sql.sq('a.vec', 'b.vec')}) <= 0.1")
def doc_near_duplicates(spark, d):
    return neat(near_pairs(X.text_counts(load(spark, d, "documents", "doc_id", "text"), "doc_id", "text"), X.unit_vectors, 0.1))


@query(f"WITH {sql.trigrams('documents', 'doc_id', 'text')}, dv AS MATERIALIZED (FROM tvec), {sql.trigrams('benchmark', 'item_id', 'text').replace('codes', 'codes2').replace('hashed', 'hashed2').replace('tri_n', 'tri_n2').replace('norms', 'norms2').replace('cells', 'cells2').replace('tvec', 'bvec')}, near AS (SELECT b.vec_id AS query_id, dv.vec_id, sqrt({sql.sq('b.vec', 'dv.vec')}) AS dist FROM bvec b, dv) SELECT query_id, rank, vec_id, round(dist, 6) + 0.0 AS dist FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS INTEGER) AS rank FROM near) WHERE rank <= 3")
def benchmark_to_documents(spark, d):
    return neat(E.exact_knn(X.document_vectors(spark, d), X.benchmark_vectors(spark, d), 3, self_match="include"))


_LINE = "SELECT l_orderkey, l_linenumber, l_partkey, " + ", ".join(f"({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () AS z{i}" for i, c in enumerate(["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE))"])) + " FROM lineitem"


@query(f"WITH z AS ({_LINE}) SELECT " + ", ".join(f"round(z{i}, 4) + 0.0 AS z{i}" for i in range(6)) + " FROM z")
def lineitem_vectors(spark, d):
    return X.lineitem_vectors(spark, d).select(*(r6(F.get("vec", F.lit(i)), 4).alias(f"z{i}") for i in range(6)))


@query("SELECT user_id, CAST(sum(n) AS BIGINT) AS n_events, count(*) AS n_slots, CAST(max(n) AS BIGINT) AS top FROM (SELECT user_id, event_type, hour(ts) AS h, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")
def user_profile_vectors(spark, d):
    return X.user_counts(load(spark, d, "events", "user_id", "event_type", "ts")).groupBy("user_id").agg(F.sum("n").alias("n_events"), F.count("*").alias("n_slots"), F.max("n").alias("top"))


@query(f"WITH {sql.knn(10)} SELECT query_id, array_to_string(list(vec_id ORDER BY rank), ',') AS ids FROM near GROUP BY query_id")
def topk_aggregate(spark, d):
    """The grouped aggregate over distances of a stated query set."""
    from .functions.udfs import topk_agg

    base, q = split(spark, d)
    near = E.exact_knn(base, q, 30)
    return near.groupBy("query_id").agg(topk_agg("vec_id", "dist").alias("ids")).select("query_id", F.array_join(F.col("ids").cast("array<string>"), ",").alias("ids"))


@query("SELECT dim, count(*) AS n, round(avg(x), 6) + 0.0 AS mean FROM (SELECT generate_subscripts(embedding, 1) - 1 AS dim, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings) GROUP BY dim")
def explode_dims(spark, d):
    from .functions.udfs import register_udfs

    register_udfs(spark)
    emb(spark, d).select("vec_id", "vec").createOrReplaceTempView("vecs")
    return spark.sql("SELECT dim, count(*) AS n, round(avg(x), 6) + 0.0D AS mean FROM explode_dims(TABLE(vecs)) GROUP BY dim")


@query(f"{_PQ_SCAN} SELECT query_id, vec_id, round(dist, 4) + 0.0 AS dist FROM scan WHERE query_id % 50 = 0")
def adc_function(spark, d):
    """The look-up as an Arrow function over (table, code)."""
    from .functions.udfs import adc_distance

    base, q = split(spark, d)
    c = _pq(spark, d)
    table = _adt(q.where("vec_id % 50 = 0"), c).groupBy(F.col("vec_id").alias("query_id")).agg(F.sort_array(F.collect_list(F.struct("m", "code", "d"))).alias("t")).select("query_id", F.col("t.d").alias("adt"))
    met = c.encode(base).select("vec_id", "code").join(F.broadcast(table))  # a stated query set against all codes
    return met.select("query_id", "vec_id", r6(adc_distance("adt", "code"), 4).alias("dist"))


@query(f"WITH {sql.selection(24, 8)}, kept2 AS (SELECT src, {sql.select_fold('c', 8, 0.02)} AS nbrs FROM lists), a AS (SELECT src, unnest(nbrs).id AS dst, 1 AS a FROM kept), b AS (SELECT src, unnest(nbrs).id AS dst, 1 AS b FROM kept2) SELECT count(a) FILTER (b IS NOT NULL) AS n_both, count(a) FILTER (b IS NULL) AS n_only_strict, count(b) FILTER (a IS NULL) AS n_only_relaxed FROM a FULL OUTER JOIN b USING (src, dst)")
def graph_diff(spark, d):
    """Edges that two selections share and edges of one only: a full outer join."""
    lists = stored(_lists(spark, d), "lists")
    a, b = (G.edges_of(G.select_neighbours(lists, 8, tau)).select("src", "dst", F.lit(1).alias(n)) for n, tau in (("a", 0.0), ("b", 0.02)))
    both = a.join(b, ["src", "dst"], "full")
    n = lambda c: F.sum(c.cast("long"))
    return both.agg(n(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("n_both"), n(F.col("b").isNull()).alias("n_only_strict"), n(F.col("a").isNull()).alias("n_only_relaxed"))


@query(f"WITH emb AS ({sql.EMB}), n AS (SELECT sqrt({sql.dot('vec', 'vec')}) AS z FROM emb) SELECT round(quantile_disc(z, 0.25), 6) + 0.0 AS q25, round(quantile_disc(z, 0.5), 6) + 0.0 AS q50, round(quantile_disc(z, 0.9), 6) + 0.0 AS q90 FROM n")
def norm_quantiles(spark, d):
    """Quantiles of the norms from a sketch whose rank error is below one row here."""
    z = emb(spark, d).select(F.sqrt(V.norm_sq("vec")).alias("z"))
    return z.agg(F.percentile_approx("z", [0.25, 0.5, 0.9], 1_000_000).alias("q")).select(*(r6(F.get("q", F.lit(i))).alias(n) for i, n in enumerate(("q25", "q50", "q90"))))


@query("WITH f AS (SELECT label, generate_subscripts(embedding, 1) - 1 AS dim, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings), g AS (SELECT label, sum(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))) AS trace FROM embeddings GROUP BY label), c AS (SELECT label, dim, avg(x) AS x FROM f GROUP BY 1, 2) SELECT c.label, CAST(dim AS INTEGER) AS dim, round(c.x, 5) + 0.0 AS x, round(trace, 4) + 0.0 AS trace FROM c JOIN g ON c.label IS NOT DISTINCT FROM g.label")
def centroid_aggregate(spark, d):
    """Mean vectors and the trace of the Gram matrix by label, as aggregate functions in SQL."""
    from .functions.udfs import register_udfs

    register_udfs(spark)
    v = emb(spark, d).select("label", "vec")
    v.createOrReplaceTempView("labelled_vectors")
    got = spark.sql("SELECT label, centroid_agg(vec) AS c, gram_agg(vec) AS g FROM labelled_vectors GROUP BY label")
    dim = 64
    trace = F.aggregate(F.array(*[F.lit(i * dim - i * (i - 1) // 2) for i in range(dim)]), F.lit(0.0), lambda s, i: s + F.get("g", i))
    return got.select("label", r6(trace, 4).alias("trace"), F.posexplode("c").alias("dim", "x")).select("label", "dim", r6("x", 5).alias("x"), "trace")


@query(f"WITH emb AS ({sql.EMB}), p AS (SELECT a.vec_id AS a, b.vec_id AS b, a.vec AS av, b.vec AS bv FROM emb a JOIN emb b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id) SELECT a, b, round({sql.dot('av', 'bv')} / (sqrt({sql.dot('av', 'av')}) * sqrt({sql.dot('bv', 'bv')})), 6) + 0.0 AS cosine, {sql.sq('av', 'bv')} < {sql.dot('av', 'av')} AS admitted, CAST(floor(-ln(((b % 2147483648 * 2654435761 + 42) % 4294967296 + 1) / 4294967296.0) / ln(16.0)) AS INTEGER) AS level, CAST(b % 2147483648 * 2654435761 % 4294967296 % 4 AS INTEGER) AS segment FROM p")
def sql_surface(spark, d):
    """More of the SQL surface: cosine, admission against the origin (whose squared distance from a is the norm of a), levels and segments."""
    _pair_view(spark, d, "l2_sq", "dot")
    return spark.sql("SELECT a, b, round(dot / (sqrt(na) * sqrt(nb)), 6) + 0.0D AS cosine, l2_sq < na AS admitted, vec_level(b, 16D) AS level, vec_segment(b, 4) AS segment FROM vec_pairs")


@query()
def codec_reports(spark, d):
    v, out = emb(spark, d), None
    for name, c in (("sq", C.ScalarCodec(4)), ("pca", C.PrincipalCodec()), ("pq", C.ProductCodec(8, 4, 2, sample=0)), ("acc", C.AlignedCodec(16, iters=2, sample=0)), ("acc quantile", C.AlignedCodec(16, iters=2, sample=0, rule="quantile", rounding="nearest"))):
        one = C.codec_report(c.fit(v), v).withColumn("codec", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT source, count(*) AS n, 64 AS dim FROM embeddings, (VALUES ('csv'), ('json'), ('orc')) s(source) GROUP BY source")
def file_sources(spark, d):
    """Vectors written to and read from csv, json and orc files."""
    from .sources.tables import shared_dir

    v, out = emb(spark, d).select("vec_id", "vec"), None
    paths = {k: shared_dir(spark, f"vectors-{k}") for k in ("csv", "json", "orc")}
    v.select("vec_id", F.array_join(F.col("vec").cast("array<string>"), " ")).write.csv(paths["csv"])
    v.write.json(paths["json"])
    v.write.orc(paths["orc"])
    got = {"csv": X.from_csv(spark, paths["csv"]), "json": X.from_json(spark, paths["json"]), "orc": spark.read.orc(paths["orc"])}
    for k, df in got.items():
        one = df.select(F.lit(k).alias("source"), F.size("vec").alias("dim")).groupBy("source", "dim").agg(F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out.select("source", "n", "dim")


@query()
def plan_costs(spark, d):
    """Exchanges, joins and Python stages that Spark plans for a hop with and without codes beside the ids, and for search and rerank."""
    base, q = split(spark, d)
    edges = G.edges_of(_bulk(spark, d))
    codes = _pq(spark, d).encode(emb(spark, d)).select("vec_id", "code")
    front = q.select(F.col("vec_id").alias("src")).hint("merge")
    apart = edges.join(front, "src").join(codes.hint("merge").withColumnRenamed("vec_id", "dst"), "dst")
    blocks = stored(G.pack_blocks(edges, codes), "blocks")
    rows = [(n, k, v) for n, df in (("hop, codes apart", apart), ("hop, codes beside ids", blocks.join(front, "src")), ("exact search", E.exact_knn(base, q, 10))) for k, v in M.plan_cost(df).items()]
    return spark.createDataFrame(rows, "plan string, what string, n int")


# -- workloads, streams and the rest are added by their modules
from .plans import graph_queries, workloads  # noqa: E402, F401
from .streaming import queries as _stream_queries  # noqa: E402, F401
