"""Vector codecs: none, scalar, principal components, product, and aligned compact codes.

Each fits on a DataFrame of vectors, encodes and decodes in Arrow batches without a shuffle, and gives the graph kernels a distance source. Models are small arrays
(at most a few MB, fixed by their parameters), which are broadcast. Training is distributed: every step sends sums, never vectors."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import LazyTables, Points, Tables

FIXED = float(1 << 30)


def matrix(column: pa.Array) -> np.ndarray:
    """(rows, dim) of a list column without nulls."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1).astype(np.float64)


def to_lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x).reshape(-1)))


SORTED_ROWS, HASH_SHIFT = 1 << 14, 20  # rows that one task sorts, bits of the hash within a range of it


def stable_sample(vectors: DataFrame, size: int, seed: int = 42) -> DataFrame:
    """`size` vectors of lowest hash of their id: the same rows whatever the partitioning, so a smaller sample is one of a larger too. Of a larger one only the rows of the last
    range of hashes are sorted, as the ranges before it are whole."""
    h = (F.pmod(F.col("vec_id"), F.lit(1 << 31)) * F.lit(2654435761) + F.lit(seed)) % F.lit(1 << 32)
    rows, whole = vectors.withColumn("_h", h), None
    if size > SORTED_ROWS:
        part = F.shiftright("_h", HASH_SHIFT)
        last, before = None, 0
        for r in sorted(rows.groupBy(part.alias("part")).count().collect()):
            if before + r["count"] > size:
                last = r["part"]
                break
            before += r["count"]
        if last is None:
            return vectors
        whole, rows, size = rows.where(part < last), rows.where(part == last), size - before
    sample = rows.orderBy("_h", "vec_id").limit(size)
    return (sample if whole is None else whole.unionByName(sample)).drop("_h")


def split_dims(dim: int, parts: int) -> list[tuple[int, int]]:
    """Contiguous parts of nearly equal size; the first dim mod parts are one longer."""
    q, r = divmod(dim, parts)
    cut = [0]
    for m in range(parts):
        cut.append(cut[-1] + q + (m < r))
    return list(zip(cut[:-1], cut[1:], strict=True))


def code_length(k: int) -> int:
    return max(0, math.ceil(math.log2(k)))


class ExactCodec:
    """Full vectors."""

    name = "exact"

    def fit(self, vectors: DataFrame) -> ExactCodec:
        self.dim = len(vectors.select("vec").first()[0])
        return self

    # numpy side
    def codes(self, x: np.ndarray) -> np.ndarray:
        return x

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        return codes.astype(np.float64)

    def source(self, x: np.ndarray, **_: object) -> Points:
        return Points(self.codes(x).astype(np.float32))

    def query_state(self, q: np.ndarray) -> np.ndarray:
        return self.codes(q).astype(np.float32)

    def bytes_per_vector(self) -> float:
        return 4.0 * self.dim

    # DataFrame side
    code_type = "array<double>"

    def encode(self, vectors: DataFrame) -> DataFrame:
        """vectors with `code`."""
        sent = vectors.sparkSession.sparkContext.broadcast(self)

        @F.arrow_udf(self.code_type)
        def encoded(v: pa.Array) -> pa.Array:
            c = sent.value.codes(matrix(v))
            return to_lists(c if "double" in sent.value.code_type else c.astype(np.int32))

        return vectors.withColumn("code", encoded(F.col("vec")))

    def decode(self, coded: DataFrame) -> DataFrame:
        """coded with `decoded`."""
        sent = coded.sparkSession.sparkContext.broadcast(self)

        @F.arrow_udf("array<double>")
        def plain(c: pa.Array) -> pa.Array:
            return to_lists(sent.value.decoded(matrix(c)))

        return coded.withColumn("decoded", plain(F.col("code")))


class ScalarCodec(ExactCodec):
    """Each dimension on 2^bits levels between its least and largest value."""

    name, code_type = "sq", "array<int>"

    def __init__(self, bits: int = 8, rounding: str = "nearest"):
        self.bits, self.rounding = bits, rounding

    def ranges(self, vectors: DataFrame) -> DataFrame:
        return vectors.select(F.posexplode("vec").alias("dim", "x")).groupBy("dim").agg(F.min("x").alias("lo"), F.max("x").alias("hi"))

    def fit(self, vectors: DataFrame) -> ScalarCodec:
        got = sorted(self.ranges(vectors).collect())
        self.dim = len(got)
        self.lo, hi = np.array([r["lo"] for r in got]), np.array([r["hi"] for r in got])
        self.step = (hi - self.lo) / (2**self.bits - 1)
        return self

    def codes(self, x: np.ndarray) -> np.ndarray:
        scaled = (x - self.lo) / np.where(self.step > 0, self.step, 1)
        level = np.floor(scaled + 0.5) if self.rounding == "nearest" else np.floor(scaled)
        return np.where(self.step > 0, np.clip(level, 0, 2**self.bits - 1), 0).astype(np.int32)

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        return self.lo + codes * self.step

    def source(self, x: np.ndarray, **_: object) -> Points:
        return Points(self.codes(x).astype(np.int16 if self.bits < 16 else np.int32), (self.step**2).astype(np.float32))

    def query_state(self, q: np.ndarray) -> np.ndarray:
        return self.codes(q).astype(np.int16 if self.bits < 16 else np.int32)

    def bytes_per_vector(self, packed: bool = False) -> float:
        """2 and 4 bits are held in bytes unless packed."""
        return self.dim * self.bits / 8 if packed or self.bits >= 8 else float(self.dim)


def moments(vectors: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """(n, mean, covariance by 1/n): one pass; each task sends one Gram matrix, rows of which are summed by key."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, g = 0, None, None
        for b in batches:
            if len(b):
                x = matrix(b["vec"])
                n, s, g = n + len(x), x.sum(axis=0) + (0 if s is None else s), x.T @ x + (0 if g is None else g)
        if n:
            rows = np.vstack([g, s[None, :]])
            yield pa.record_batch({"row": np.arange(len(rows)), "n": np.full(len(rows), n), "x": to_lists(rows)})

    parts = vectors.select("vec").mapInArrow(partial, "row long, n long, x array<double>")
    cells = parts.select("row", "n", F.posexplode("x").alias("col", "x")).groupBy("row", "col").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
    got = cells.toArrow()
    d = int(got["col"].to_numpy().max()) + 1
    full = np.zeros((d + 1, d))
    full[got["row"].to_numpy(), got["col"].to_numpy()] = got["x"].to_numpy()
    n = int(got["n"][0].as_py())
    mean = full[d] / n
    return n, mean, full[:d] / n - np.outer(mean, mean)


def principal_axes(covariance: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues falling and basis rows, each with its largest entry positive."""
    values, vectors = np.linalg.eigh(covariance)
    values, basis = np.maximum(values[::-1], 0), vectors[:, ::-1].T
    sign = np.sign(basis[np.arange(len(basis)), np.abs(basis).argmax(axis=1)])
    return values, basis * np.where(sign == 0, 1, sign)[:, None]


def variance_curve(values: np.ndarray) -> np.ndarray:
    total = values.sum()
    return np.cumsum(values) / total if total > 0 else np.ones(len(values))


class PrincipalCodec(ExactCodec):
    """The first principal components; dims, or as many as reach the share alpha of the variance."""

    name = "pca"

    def __init__(self, alpha: float = 0.9, dims: int | None = None, basis: str = "eigen", center: bool = False):
        self.alpha, self.dims, self.kind, self.center = alpha, dims, basis, center

    def fit(self, vectors: DataFrame) -> PrincipalCodec:
        _, self.mean, cov = moments(vectors)
        self.dim = len(self.mean)
        if self.kind == "variance-order":  # only orders the dimensions by falling variance
            order = np.lexsort((np.arange(self.dim), -np.floor(np.diag(cov) * (1 << 20))))
            self.values, self.basis = np.diag(cov)[order], np.eye(self.dim)[order]
        else:
            self.values, self.basis = principal_axes(cov)
        curve = variance_curve(self.values)
        self.kept = self.dims or int(min(self.dim, np.searchsorted(curve, self.alpha - 1e-12) + 1))
        self.basis_kept = self.basis[: self.kept]
        return self

    def codes(self, x: np.ndarray) -> np.ndarray:
        return (x - self.mean if self.center else x) @ self.basis_kept.T

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        return codes @ self.basis_kept + (self.mean if self.center else 0)

    def source(self, x: np.ndarray, **_: object) -> Points:
        return Points(self.codes(x).astype(np.float32))

    def query_state(self, q: np.ndarray) -> np.ndarray:
        return self.codes(q).astype(np.float32)

    def bytes_per_vector(self) -> float:
        return 4.0 * self.kept


TABLES_BYTES = 32 << 20  # distances to centroids that a task keeps or computes at once


def nearest_centroids(x: np.ndarray, books: list[np.ndarray], parts: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """(rows, M) ids of the nearest centroids, ties to the smaller, and (rows, M, K) squared distances; missing centroids are infinitely far."""
    k = max(len(b) for b in books)
    d = np.full((len(x), len(parts), k), np.inf)
    for m, ((a, b), book) in enumerate(zip(parts, books, strict=True)):
        for s in range(0, len(x), 128):  # as many rows as stay in the cache
            rows = x[s : s + 128]
            acc, diff = np.zeros((len(rows), len(book))), np.empty((len(rows), len(book)))
            for j in range(b - a):
                np.subtract(rows[:, a + j, None], book[None, :, j], out=diff)
                np.multiply(diff, diff, out=diff)
                acc += diff
            d[s : s + 128, m, : len(book)] = acc
    return d.argmin(axis=2), d


def nearest_codes(x: np.ndarray, books: list[np.ndarray], parts: list[tuple[int, int]]) -> np.ndarray:
    """The ids alone. A matrix product finds the nearest where no other centroid is nearly as near; the others are measured by `nearest_centroids`."""
    out = np.zeros((len(x), len(parts)), np.int64)
    for m, ((a, b), book) in enumerate(zip(parts, books, strict=True)):
        size = (book * book).sum(axis=1)
        for s in range(0, len(x), 256):
            rows = x[s : s + 256, a:b]
            near = size[None, :] - 2 * (rows @ book.T)
            best = near.argmin(axis=1)
            slack = 1e-9 * (1 + (rows * rows).sum(axis=1) + size.max())
            close = np.flatnonzero(((near <= (near[np.arange(len(rows)), best] + slack)[:, None]).sum(axis=1) != 1))
            if len(close):
                best[close] = nearest_centroids(rows[close], [book], [(0, b - a)])[0][:, 0]
            out[s : s + 256, m] = best
    return out


def train_codebooks(vectors: DataFrame, parts: list[tuple[int, int]], k: int, iters: int) -> list[np.ndarray]:
    """Lloyd's algorithm for all subspaces at once. It starts from the k vectors of lowest id; every iteration is one pass in which tasks send counts and
    fixed-point sums per (subspace, centroid), so the result does not depend on the order of rows. An empty centroid stays."""
    first = vectors.orderBy("vec_id").limit(k).select("vec").collect()
    start = np.array([r[0] for r in first])
    books = [start[:, a:b].copy() for a, b in parts]
    width = max(b - a for a, b in parts)
    for _ in range(iters):
        sent = vectors.sparkSession.sparkContext.broadcast(books)

        def partial(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            sums, counts = np.zeros((len(parts), k, width), np.int64), np.zeros((len(parts), k), np.int64)
            for batch in batches:
                if not len(batch):
                    continue
                x = matrix(batch["vec"])
                codes = nearest_codes(x, sent.value, parts)
                fixed = np.floor(x * FIXED).astype(np.int64)
                for m, (a, b) in enumerate(parts):
                    np.add.at(sums[m, :, : b - a], codes[:, m], fixed[:, a:b])
                    counts[m] += np.bincount(codes[:, m], minlength=k)
            m, c = np.nonzero(counts)
            yield pa.record_batch({"m": m, "c": c, "n": counts[m, c], "s": to_lists(sums[m, c])}) if len(m) else pa.record_batch({"m": m, "c": c, "n": counts[m, c], "s": pa.array([], pa.list_(pa.int64()))})

        cells = vectors.select("vec").mapInArrow(partial, "m long, c long, n long, s array<long>").select("m", "c", "n", F.posexplode("s").alias("j", "s"))
        got = cells.groupBy("m", "c", "j").agg(F.sum("n").alias("n"), F.sum("s").alias("s")).toArrow()  # a number for each component of the books
        at_m, at_c, at_j, n, total = (got[x].to_numpy() for x in ("m", "c", "j", "n", "s"))
        for m, (a, b) in enumerate(parts):
            some = (at_m == m) & (at_j < b - a)
            books[m][at_c[some], at_j[some]] = total[some].astype(np.float64) / (n[some].astype(np.float64) * FIXED)
    return books


def centroid_distances(books: list[np.ndarray]) -> np.ndarray:
    """(M, K, K) squared distances between the centroids of each subspace."""
    k = max(map(len, books))
    out = np.full((len(books), k, k), np.inf)
    for m, b in enumerate(books):
        acc = np.zeros((len(b), len(b)))
        for j in range(b.shape[1]):
            diff = b[:, None, j] - b[None, :, j]
            acc += diff * diff
        out[m, : len(b), : len(b)] = acc
    return out


class ProductCodec(ExactCodec):
    """M contiguous subspaces with 2^L centroids each."""

    name, code_type = "pq", "array<int>"

    def __init__(self, m: int = 8, bits: int = 8, iters: int = 8, sample: int = 20_000):
        self.m, self.bits, self.iters, self.sample = m, bits, iters, sample

    def _train(self, vectors: DataFrame, dim: int) -> None:
        self.parts = split_dims(dim, self.m)
        self.books = train_codebooks(vectors, self.parts, 1 << self.bits, self.iters)
        self.between = centroid_distances(self.books)

    def fit(self, vectors: DataFrame) -> ProductCodec:
        self.dim = len(vectors.select("vec").first()[0])
        self._train(stable_sample(vectors.select("vec_id", "vec"), self.sample) if self.sample else vectors, self.dim)
        return self

    def codes(self, x: np.ndarray) -> np.ndarray:
        return nearest_codes(x, self.books, self.parts).astype(np.int32)

    def tables(self, x: np.ndarray) -> np.ndarray:
        return nearest_centroids(x, self.books, self.parts)[1]

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        codes = codes.astype(np.int64)
        return np.concatenate([b[codes[:, m]] for m, b in enumerate(self.books)], axis=1)

    def source(self, x: np.ndarray, **how: object) -> Tables:
        codes = nearest_codes(x, self.books, self.parts)
        own = LazyTables(self, x) if self.lazy(len(x)) else self.table_rows(x)
        return Tables(codes.astype(np.int16), own, self.between.astype(np.float32), np.float32)

    def table_rows(self, x: np.ndarray) -> np.ndarray:
        return self.tables(x).astype(np.float32)

    def lazy(self, n: int) -> bool:
        """Whether the tables of n vectors are better computed when asked for than kept."""
        return n * self.m * 4 << self.bits > TABLES_BYTES

    def query_state(self, q: np.ndarray) -> np.ndarray:
        return self.tables(q).astype(np.float32)

    def bytes_per_vector(self) -> float:
        return self.m * self.bits / 8


class AlignedCodec(ProductCodec):
    """Aligned compact codes: principal components, then subspaces of 2^L = 16 centroids, and tables quantised to H bits with one range for the vector-to-centroid
    and centroid-to-centroid tables, so that sums of both compare. Codes and a vector's table come from the same distances."""

    name = "acc"

    def __init__(self, m: int = 16, bits: int = 4, table_bits: int | None = 8, dims: int | None = None, alpha: float = 0.9, iters: int = 8, sample: int = 20_000, rule: str = "sum_of_max", rounding: str = "floor", quantile: float = 0.99, pca: bool = True, basis: str = "eigen", inline: bool = True, block: int = 0):
        super().__init__(m, bits, iters, sample)
        self.table_bits, self.rule, self.rounding, self.quantile, self.inline, self.block = table_bits, rule, rounding, quantile, inline, block
        self.axes = PrincipalCodec(alpha, dims, basis) if pca else None

    def fit(self, vectors: DataFrame) -> AlignedCodec:
        self.dim = len(vectors.select("vec").first()[0])
        sample = stable_sample(vectors.select("vec_id", "vec"), self.sample) if self.sample else vectors
        if self.axes:
            self.axes.fit(vectors)
            rotated = self.axes.encode(sample).select("vec_id", F.col("code").alias("vec"))
            self.m = min(self.m, self.axes.kept)
            self._train(rotated, self.axes.kept)
        else:
            rotated = sample
            self._train(sample, self.dim)
        self.lo, self.range = table_range(rotated, self)
        return self

    def turned(self, x: np.ndarray) -> np.ndarray:
        return self.axes.codes(x) if self.axes else x

    def codes(self, x: np.ndarray) -> np.ndarray:
        return super().codes(self.turned(x))

    def tables(self, x: np.ndarray) -> np.ndarray:
        return super().tables(self.turned(x))

    def decoded(self, codes: np.ndarray) -> np.ndarray:
        out = super().decoded(codes)
        return self.axes.decoded(out) if self.axes else out

    def quantised(self, d: np.ndarray) -> np.ndarray:
        if self.table_bits is None:
            return d.astype(np.float32)
        return quantise(d, self.lo, self.range, self.table_bits, self.rounding)

    def source(self, x: np.ndarray, **how: object) -> Tables:
        codes, d = nearest_centroids(self.turned(x), self.books, self.parts)
        wide = np.float32 if self.table_bits is None else np.uint16 if self.table_bits <= 10 else np.int32
        return Tables(codes.astype(np.int16), self.quantised(d), self.quantised(self.between), wide, int(how.get("block", self.block)))

    def query_state(self, q: np.ndarray) -> np.ndarray:
        return self.quantised(self.tables(q))

    def encode_with_tables(self, vectors: DataFrame) -> DataFrame:
        """vectors with `code` and `adt` (the quantised table, M x K) from one pass over the distances."""
        sent = vectors.sparkSession.sparkContext.broadcast(self)

        @F.arrow_udf("struct<code array<int>, adt array<int>>")
        def both(v: pa.Array) -> pa.Array:
            s = sent.value
            codes, d = nearest_centroids(s.turned(matrix(v)), s.books, s.parts)
            return pa.StructArray.from_arrays([to_lists(codes.astype(np.int32)), to_lists(s.quantised(d).reshape(len(d), -1).astype(np.int32))], ["code", "adt"])

        return vectors.withColumn("_b", both(F.col("vec"))).withColumns({"code": F.col("_b.code"), "adt": F.col("_b.adt")}).drop("_b")


def quantise(d: np.ndarray, lo: float, rng: float, bits: int, rounding: str = "floor") -> np.ndarray:
    """Distances on 2^bits - 1 steps of the range; what lies outside is clamped, a range of 0 gives 0."""
    top = 2**bits - 1
    kind = np.uint8 if bits <= 8 else np.uint16
    if rng <= 0:
        return np.zeros(np.shape(d), kind)
    level = (np.where(np.isfinite(d), d, lo + rng) - lo) / rng * top
    return np.clip(np.floor(level if rounding == "floor" else level + 0.5), 0, top).astype(kind)


def table_range(points: DataFrame, codec: ProductCodec) -> tuple[float, float]:
    """(least, range) of the table quantiser over the tables of a sample and the centroid table. Rule sum_of_max: from the least of all entries to the sum of each subspace's
    largest; observed_max: to the largest sum met among sample pairs; quantile: to that quantile of those sums."""
    sent = points.sparkSession.sparkContext.broadcast(codec)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = sent.value
        for b in batches:
            if len(b):
                codes, d = nearest_centroids(matrix(b["vec"]), c.books, c.parts)
                finite = np.where(np.isfinite(d), d, -1)
                sums = np.take_along_axis(d, codes[np.arange(len(d))[::-1]][:, :, None], axis=2)[:, :, 0].sum(axis=1)
                yield pa.record_batch({"m": np.arange(d.shape[1]), "lo": d.min(axis=(0, 2)), "hi": finite.max(axis=(0, 2)), "sums": pa.array([np.sort(sums)[:: max(1, len(sums) // 512)].tolist()] + [[]] * (d.shape[1] - 1), pa.list_(pa.float64()))})

    got = points.select("vec").mapInArrow(partial, "m long, lo double, hi double, sums array<double>").toArrow()
    m, lo, hi = (got[c].to_numpy() for c in ("m", "lo", "hi"))
    finite = np.where(np.isfinite(codec.between), codec.between, -1)
    top = np.array([max(hi[m == i].max(initial=0), finite[i].max()) for i in range(len(codec.parts))])
    least = float(min(lo.min(initial=np.inf), codec.between.min()))
    if codec.rule == "sum_of_max":
        return least, float(top.sum() - least)
    sums = np.concatenate([np.array(x.as_py()) for x in got["sums"]] or [np.zeros(1)])
    return least, float((sums.max() if codec.rule == "observed_max" else np.quantile(sums, codec.quantile)) - least)


CODECS = {"exact": ExactCodec, "sq": ScalarCodec, "pca": PrincipalCodec, "pq": ProductCodec, "acc": AlignedCodec}


def register_codec(name: str, cls: type[ExactCodec]) -> None:
    """Codecs plug into building and searching by name, e.g. a rotated product codec."""
    CODECS[name] = cls


def codec_report(codec: ExactCodec, vectors: DataFrame) -> DataFrame:
    """One row: mean relative error of the decoded form, distinct codes and vectors, and for quantised tables the entries clamped above and sums that pass the bits of an entry."""
    from ..functions.vectors import l2_sq, norm_sq

    both = codec.decode(codec.encode(vectors))
    base = both.agg(F.avg(l2_sq("vec", "decoded") / norm_sq("vec")).alias("rel_error"), F.count_distinct("code").alias("codes"), F.count_distinct("vec").alias("vectors"), F.lit(float(codec.bytes_per_vector())).alias("code_bytes"))
    if not isinstance(codec, AlignedCodec) or codec.table_bits is None:
        return base.withColumns({"clamped": F.lit(0).cast("long"), "overflows": F.lit(0).cast("long")})
    top = 2**codec.table_bits - 1
    tables = codec.encode_with_tables(vectors).select(F.size(F.filter("adt", lambda x: x >= top)).alias("clamped"), F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(codec.m - 1)), lambda m: F.array_max(F.slice("adt", m * codec.between.shape[1] + 1, F.lit(codec.between.shape[1])))), F.lit(0), lambda s, x: s + x).alias("most"))
    sums = tables.agg(F.sum("clamped").cast("long").alias("clamped"), F.sum((F.col("most") > top).cast("long")).alias("overflows"))
    return base.join(sums, how="cross")  # one row each
