"""Vector sets (vec_id long, vec array<double>, ...) from the given tables and from files."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .tables import load

HELD_OUT = 10


def embedding_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("vec"), "label")


def trigram_counts(texts: pa.Array, dim: int) -> np.ndarray:
    """(texts, dim) counts of hashed trigrams of code points of the lower-case text."""
    out = np.zeros((len(texts), dim), np.int64)
    for i, t in enumerate(pc.utf8_lower(pc.fill_null(texts, "")).to_pylist()):
        c = np.frombuffer(t.encode("utf-32-le"), np.uint32).astype(np.int64)
        if len(c) > 2:
            out[i] = np.bincount((c[:-2] * 961 + c[1:-1] * 31 + c[2:]) % dim, minlength=dim)
    return out


def text_vectors(df: DataFrame, id_col: str, text_col: str, dim: int = 256) -> DataFrame:
    """Unit vectors of hashed trigram counts; texts of under three characters have none and are left out."""

    @F.arrow_udf("array<double>")
    def vectors(texts: pa.Array) -> pa.Array:
        counts = trigram_counts(texts, dim)
        norm = np.sqrt((counts * counts).sum(axis=1).astype(np.float64))
        unit = counts / np.maximum(norm, 1e-300)[:, None]
        offsets = np.arange(len(texts) + 1, dtype=np.int32) * dim
        return pa.ListArray.from_arrays(pa.array(offsets), pa.array(unit.reshape(-1)), mask=pa.array(norm == 0))

    return df.select(F.col(id_col).cast("long").alias("vec_id"), vectors(F.col(text_col)).alias("vec")).where("vec is not null")


def text_counts(df: DataFrame, id_col: str, text_col: str, dim: int = 256) -> DataFrame:
    """(vec_id, packed): the counts that text_vectors divides by their length, as unsigned numbers of 2 bytes, or of 4 where one does not fit."""

    @F.arrow_udf("binary")
    def packed(texts: pa.Array) -> pa.Array:
        pieces = (trigram_counts(texts.slice(s, 256), dim) for s in range(0, len(texts), 256))
        return pa.array([c.astype("<u2" if c.max() < 1 << 16 else "<u4").tobytes() if c.any() else None for counts in pieces for c in counts], pa.binary())

    return df.select(F.col(id_col).cast("long").alias("vec_id"), packed(F.col(text_col)).alias("packed")).where("packed is not null")


def unit_vectors(packed: pa.Array, dim: int = 256) -> np.ndarray:
    """The unit vectors of packed counts, to the bit those of text_vectors."""
    counts = np.array([np.frombuffer(c, "<u2" if len(c) == 2 * dim else "<u4") for c in packed.to_pylist()], np.int64).reshape(-1, dim)
    return counts / np.sqrt((counts * counts).sum(axis=1).astype(np.float64))[:, None]


def document_vectors(spark: SparkSession, sf_dir: str, dim: int = 256) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "documents", "doc_id", "text"), "doc_id", "text", dim)


def page_vectors(spark: SparkSession, sf_dir: str, dim: int = 256) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "pages", "page_id", "html"), "page_id", "html", dim)


def conversation_vectors(spark: SparkSession, sf_dir: str, dim: int = 256) -> DataFrame:
    turns = load(spark, sf_dir, "conversations", "conv_id", "turn", "text").withColumn("id", F.col("conv_id") * 100 + F.col("turn"))
    return text_vectors(turns, "id", "text", dim)


def benchmark_vectors(spark: SparkSession, sf_dir: str, dim: int = 256) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "benchmark", "item_id", "text"), "item_id", "text", dim)


def numeric_vectors(df: DataFrame, id_col: Column | str, cols: dict[str, Column], keep: tuple[str, ...] = ()) -> DataFrame:
    """z-scores of the columns (columns to `keep` pass through) with the population deviation; a constant column gives 0. One aggregate of two numbers a column."""
    raw = df.select((F.col(id_col) if isinstance(id_col, str) else id_col).cast("long").alias("vec_id"), *keep, *(c.cast("double").alias(n) for n, c in cols.items()))
    stats = raw.agg(*(F.avg(n).alias(f"m_{n}") for n in cols), *(F.stddev_pop(n).alias(f"s_{n}") for n in cols)).first()
    z = [((F.col(n) - F.lit(stats[f"m_{n}"])) / F.lit(stats[f"s_{n}"])) if stats[f"s_{n}"] else F.lit(0.0) for n in cols]
    return raw.select("vec_id", *keep, F.array(*z).alias("vec"))


def lineitem_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six numbers of each line. Ids are a 60-bit hash of the whole row: the keys repeat, and a rank would need all rows in one order."""
    rows = load(spark, sf_dir, "lineitem")
    return line_numbers(rows, F.pmod(F.xxhash64(*rows.columns), F.lit(1 << 60)))


def line_numbers(rows: DataFrame, key: Column, keep: tuple[str, ...] = ()) -> DataFrame:
    day = F.datediff("l_shipdate", F.lit("1992-01-01").cast("date"))
    return numeric_vectors(rows, key, {"quantity": F.col("l_quantity"), "price": F.col("l_extendedprice"), "discount": F.col("l_discount"), "tax": F.col("l_tax"), "line": F.col("l_linenumber"), "day": day}, keep)


def order_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "orders")
    hot = {f"status_{s}": (F.col("o_orderstatus") == s).cast("double") for s in ("F", "O", "P")} | {f"priority_{i}": F.col("o_orderpriority").startswith(str(i)).cast("double") for i in range(1, 6)}
    return numeric_vectors(rows, "o_orderkey", {"price": F.col("o_totalprice"), "day": F.datediff("o_orderdate", F.lit("1992-01-01").cast("date")), **hot})


def user_counts(events: DataFrame) -> DataFrame:
    """(user_id, slot, n): events by type and hour of the day; slot = 24 * type + hour, types in alphabetical order of their name hash."""
    kinds = ["click", "error", "purchase", "signup", "view"]  # fixed values: the event types
    number = F.coalesce(*[F.when(F.col("event_type") == k, F.lit(i)) for i, k in enumerate(kinds)], F.pmod(F.crc32(F.col("event_type").cast("binary")), F.lit(5)).cast("int"))
    return events.groupBy("user_id", (number * 24 + F.hour("ts")).alias("slot")).agg(F.count("*").alias("n"))


def user_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = user_counts(load(spark, sf_dir, "events", "user_id", "event_type", "ts"))
    packed = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("slot", "n"))).alias("m"), F.sqrt(F.sum(F.col("n") * F.col("n")).cast("double")).alias("norm"))
    return packed.select(F.col("user_id").cast("long").alias("vec_id"), F.transform(F.sequence(F.lit(0), F.lit(119)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0)) / F.col("norm")).alias("vec"))


def split_queries(vectors: DataFrame, modulus: int = HELD_OUT) -> tuple[DataFrame, DataFrame]:
    """(base, queries): ids divisible by modulus are queries and are held out of the base."""
    held = F.pmod(F.col("vec_id"), F.lit(modulus)) == 0
    return vectors.where(~held), vectors.where(held)


def validate_vectors(vectors: DataFrame) -> DataFrame:
    """One row of what is wrong with a vector set: nulls, other lengths than the commonest, NaN or infinite components, repeated ids."""
    v = vectors.select("vec_id", "vec", F.size("vec").alias("d"))
    bad = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    sums = v.agg(F.count("*").alias("n"), F.sum(F.col("vec").isNull().cast("long")).alias("n_null"), F.sum(F.coalesce(bad.cast("long"), F.lit(0))).alias("n_not_finite"), F.min("d").alias("min_dim"), F.max("d").alias("max_dim"))
    twice = v.groupBy("vec_id").count().where("count > 1").agg(F.count("*").alias("n_repeated_ids"))
    return sums.join(twice, how="cross")  # one row each


def from_csv(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """Lines `id,x x x`; lines that cannot be read have null vectors."""
    rows = spark.read.schema(T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("v", T.StringType())])).option("mode", "PERMISSIVE").csv(path)
    return rows.select("vec_id", F.transform(F.split("v", sep), lambda x: x.try_cast("double")).alias("vec"))


def from_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("vec_id long, vec array<double>").option("mode", "PERMISSIVE").json(path)


def from_raw_floats(spark: SparkSession, path: str, dim: int) -> DataFrame:
    """Files of consecutive little-endian float32 records; ids count within the order of (file, record): file number << 32 | record."""
    files = spark.read.format("binaryFile").load(path).select(F.pmod(F.xxhash64("path"), F.lit(1 << 30)).alias("file"), "content")

    def records(batches):
        for b in batches:
            for file, content in zip(b["file"], b["content"], strict=True):
                raw = content.as_py()
                x = np.frombuffer(raw[: len(raw) // (4 * dim) * 4 * dim], "<f4").astype(np.float64)
                n = len(x) // dim
                for i in range(0, n, 8192):
                    part = x[i * dim : min(n, i + 8192) * dim]
                    m = len(part) // dim
                    yield pa.record_batch({"vec_id": (file.as_py() << 32) + np.arange(i, i + m), "vec": pa.ListArray.from_arrays(pa.array(np.arange(m + 1, dtype=np.int32) * dim), pa.array(part))})

    return files.mapInArrow(records, "vec_id long, vec array<double>")
