"""When compact codes keep a comparison of distances: sampling of triples, the error condition, and a tuner built on it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import bisector_margin, comparison_error, l2_sq, vsub
from .codecs import CODECS, ExactCodec, stable_sample
from .exact import exact_knn


def sample_triples(vectors: DataFrame, size: int = 10_000, pool: int = 100, pair: tuple[int, int] = (1, 2), seed: int = 42) -> DataFrame:
    """(u, v, w, uv, vv, wv): sampled vertices with two of their nearest neighbours, by default the nearest and the second."""
    picked = stable_sample(vectors.select("vec_id", "vec"), size, seed)
    near = exact_knn(vectors, picked, max(pool, *pair) if pool else max(pair))
    at = lambda r, name: near.where(F.col("rank") == r).select(F.col("query_id").alias("u"), F.col("vec_id").alias(name))
    ids = at(pair[0], "v").join(at(pair[1], "w"), "u")
    for name in ("u", "v", "w"):
        ids = ids.join(vectors.select(F.col("vec_id").alias(name), F.col("vec").alias(f"{name}v")), name)
    return ids.select("u", "v", "w", "uv", "vv", "wv")


def decoded_triples(triples: DataFrame, codec: ExactCodec) -> DataFrame:
    """triples with the decoded form of every vector (ud, vd, wd)."""
    out = triples
    for name in ("u", "v", "w"):
        out = codec.decode(codec.encode(out.withColumn("vec", F.col(f"{name}v")))).withColumnRenamed("decoded", f"{name}d").drop("vec", "code")
    return out


def margins(triples: DataFrame, codec: ExactCodec, asymmetric: bool = False) -> DataFrame:
    """(u, v, w, margin, err, code_margin): the margin of the vectors, the error by the expanded formula, and the margin of the codes."""
    t = decoded_triples(triples, codec)
    err = comparison_error("uv", "vv", "wv", vsub("uv", "ud"), vsub("vv", "vd"), vsub("wv", "wd"), asymmetric)
    return t.select("u", "v", "w", bisector_margin("uv", "vv", "wv").alias("margin"), err.alias("err"), bisector_margin("uv" if asymmetric else "ud", "vd", "wd").alias("code_margin"))


def preserved_fraction(measured: DataFrame) -> DataFrame:
    """One row: shares of triples whose margin exceeds the error strictly, exceeds or equals it, agree in sign, and tie in codes."""
    tie = F.abs("code_margin") < 1e-12
    size, err = F.abs("margin"), F.abs("err")
    share = lambda c: F.avg(c.cast("double"))
    return measured.agg(share((size > err) & ~tie).alias("strict"), share(size >= err - 1e-12).alias("ge"), share((F.signum("margin") == F.signum("code_margin")) & ~tie).alias("agree"), share(tie).alias("ties"), F.count("*").alias("n"))


def lemma_check(triples: DataFrame) -> DataFrame:
    """(u, v, w, margin_sign, distance_sign): the sign of the margin and of the difference of squared distances; they are equal."""
    diff = l2_sq("uv", "vv") - l2_sq("uv", "wv")
    sign = lambda x: F.when(F.abs(x) < 1e-12, 0).otherwise(F.signum(x)).cast("int")
    return triples.select("u", "v", "w", sign(bisector_margin("uv", "vv", "wv")).alias("margin_sign"), sign(diff).alias("distance_sign"))


def tune_codec(vectors: DataFrame, family: str, grid: list[dict], min_fraction: float = 0.0, size: int = 10_000, pool: int = 100, confirm: bool = False) -> DataFrame:
    """Ranked settings: code bytes, strict fraction and agreement on sampled triples; `best` marks those that no other beats in both bytes and strict fraction
    and that reach min_fraction. A grid is tried setting by setting; what is collected is one row each. confirm: `recall` is the recall@10 of a graph built on the codes
    of each best setting, for held-out queries, else null."""
    from ..sources.tables import stored

    triples = stored(sample_triples(vectors, size, pool), "triples")
    rows, fitted = [], []
    for params in grid:
        codec = CODECS[family](**params).fit(vectors)
        got = preserved_fraction(margins(triples, codec)).first()
        rows.append((family, str(params), float(codec.bytes_per_vector()), got["strict"], got["agree"], got["ties"]))
        fitted.append(codec)
    best = [r[3] is not None and r[3] >= min_fraction and not any((o[2] <= r[2] and o[3] > r[3]) or (o[2] < r[2] and o[3] >= r[3]) for o in rows) for r in rows]
    seen = [confirmed(vectors, c) if b and confirm else None for c, b in zip(fitted, best, strict=True)]
    return vectors.sparkSession.createDataFrame([(*r, b, x) for r, b, x in zip(rows, best, seen, strict=True)], "family string, params string, code_bytes double, strict double, agree double, ties double, best boolean, recall double").orderBy(F.desc("best"), "code_bytes")


def confirmed(vectors: DataFrame, codec: ExactCodec, k: int = 10, ef: int = 64) -> float:
    from ..sources.vectors import split_queries
    from .measures import recall
    from .search import build_index, search

    base, queries = split_queries(vectors.select("vec_id", "vec"))
    index = build_index(base, codec, 64, 16, refit=False)
    return recall(exact_knn(base, queries, k), search(index, queries, k, ef, "codes+rerank"), k).first()["recall"]
