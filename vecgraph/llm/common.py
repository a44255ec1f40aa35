"""Shared plumbing of the text operators: scratch tables, Arrow settings, row keys and connected components."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_SPACE = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def prepare(spark: SparkSession, batch_mb: int = 16) -> None:
    """Bound the Arrow batches handed to Python by bytes, so that very long texts do not pile up in one batch."""
    for key, value in (("spark.sql.execution.arrow.maxBytesPerBatch", str(batch_mb << 20)), ("spark.sql.execution.arrow.maxRecordsPerBatch", "4096")):
        if spark.conf.get(key, None) != value:
            spark.conf.set(key, value)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which all executors share; a local session without that setting gets a folder in its temp folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = f"{tempfile.gettempdir()}/checkpoints"
    return base.rstrip("/")


def scratch_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder below the shared one."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write df as a Parquet table in the shared folder and read it back: cuts the lineage, survives lost executors."""
    spark, path = df.sparkSession, scratch_dir(df.sparkSession, name)
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(col: str = "text") -> Column:
    return F.coalesce(F.col(col).cast("string"), F.lit(""))


def ascii_lower(col: Column) -> Column:
    return F.translate(col, UPPER, LOWER)


def row_keys(id_col: str = "doc_id", text_col: str = "text") -> list[Column]:
    """Two 64-bit hashes that name a row by its id and text. They are never null; rows repeated whole share them."""
    cols = [F.col(id_col), F.col(text_col)]
    return [F.xxhash64(F.lit("a"), F.isnull(cols[1]), *cols).alias("_k1"), F.xxhash64(F.lit("b"), *cols).alias("_k2")]


def crc_bucket(col: str, modulus: int) -> Column:
    """crc32 of an id written as text, modulo; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(col).cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", name: str = "cc", rounds: int = 200) -> DataFrame:
    """(node, root): root is the least node id of the component. Alternating star contraction: every round rewires each
    node to the least neighbour, so paths halve and no node ever gathers its whole component in memory (only min and
    a join on the node id). Every round is a table in the shared folder. More than `rounds` rounds, far more than the
    logarithm of any number of nodes, raise an error: no unfinished component is returned."""
    both = lambda e: e.select("a", "b").unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    edges = materialize(edges.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a <> b").distinct(), f"{name}-edges")
    nodes = both(edges).select(F.col("a").alias("node")).distinct()
    current, before = edges, None
    for _ in range(rounds):
        # large star: neighbours above a node go to the least of its neighbourhood
        n = both(current)
        low = n.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = n.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        # small star: a node and its lower neighbours go to the least of them
        down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct()
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        small = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        current = materialize(small.where("a <> b").distinct(), f"{name}-round")
        state = current.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components not complete after {rounds} rounds")
    roots = current.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("root"))
    return nodes.join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("root"))
