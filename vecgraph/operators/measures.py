"""Accuracy, cost and size measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def recall(truth: DataFrame, result: DataFrame, k: int = 1) -> DataFrame:
    """One row: the mean over queries of the shared ids among the first k, over k."""
    hits = truth.where(F.col("rank") <= k).join(result.where(F.col("rank") <= k).select("query_id", "vec_id", F.lit(1).alias("hit")), ["query_id", "vec_id"], "left")
    return hits.groupBy("query_id").agg(F.count("hit").alias("hits")).agg((F.sum("hits") / F.count("*") / k).alias("recall"), F.count("*").alias("n_queries"))


def distance_ratio(truth: DataFrame, result: DataFrame, k: int = 1) -> DataFrame:
    """One row: the mean over queries of the mean over ranks of result distance over true distance; 1 is best. 0/0 counts as 1; x/0 and missing ranks are counted and left out."""
    pairs = truth.where(F.col("rank") <= k).select("query_id", "rank", F.col("dist").alias("t")).join(result.select("query_id", "rank", F.col("dist").alias("r")), ["query_id", "rank"], "left")
    ratio = F.when((F.col("t") == 0) & (F.col("r") == 0), F.lit(1.0)).when(F.col("t") > 0, F.col("r") / F.nullif(F.col("t"), F.lit(0.0)))
    per = pairs.withColumn("ratio", ratio).groupBy("query_id").agg(F.avg("ratio").alias("ratio"), F.sum(F.col("ratio").isNull().cast("long")).alias("left_out"))
    return per.agg(F.avg("ratio").alias("distance_ratio"), F.sum("left_out").alias("n_left_out"))


def register_loads(dim: Column, register_bits: Column, m: Column, table_bits: Column) -> tuple[Column, Column]:
    """Register loads of one distance: 32-bit components, and one table entry of each subspace."""
    return F.ceil(dim * 32 / register_bits), F.ceil(m * table_bits / register_bits)


def simd_steps(bits: Column, m: Column, k: int = 16, h: int = 8) -> dict[str, Column]:
    """Tables that a register of so many bits holds at once, look-up steps for all m subspaces, neighbours in a block."""
    held = F.greatest(F.floor(bits / (k * h)), F.lit(1))
    return {"tables_at_once": held.cast("long"), "steps": F.ceil(m / held).cast("long"), "block": (bits / h).cast("long")}


def simd_plan(spark: SparkSession, widths: list[int], m: int, k: int = 16, h: int = 8) -> DataFrame:
    """The same for each register width."""
    rows = spark.createDataFrame([(u,) for u in widths], "register_bits int")
    return rows.select("register_bits", *(c.alias(n) for n, c in simd_steps(F.col("register_bits"), F.lit(m), k, h).items()))


def access_formula(n: Column, degree: int, candidates: int) -> dict[str, Column]:
    """Expected memory accesses of one insertion among n vectors: acquisition and selection, without and with codes beside the ids."""
    hops = F.log2(F.greatest(n, F.lit(2)).cast("double"))
    return {"acquisition_plain": degree * hops, "acquisition_inlined": hops, "selection_plain": F.lit(float(candidates)), "selection_tables": F.lit(0.0)}


def index_bytes(n_vectors: Column, n_edges: Column, dim: int, method: str, *, m: int = 16, bits: int = 8, kept: int = 0) -> Column:
    """Bytes of an index: vectors or codes, and neighbour lists of 4-byte ids; aligned codes lie beside every neighbour too."""
    code = {"lg": 4.0 * dim, "sq": dim * bits / 8, "pca": 4.0 * kept, "pq": m * bits / 8, "acc": m * bits / 8}[method]
    per_edge = 4 + (m * bits / 8 if method == "acc" else 0)
    return (n_vectors * F.lit(code) + n_edges * F.lit(float(per_edge))).cast("double")


def speedup(runs: DataFrame, against: str = "exact") -> DataFrame:
    """runs (dataset, method, total): how many times faster than the reference method on the same data."""
    base = runs.where(F.col("method") == against).select("dataset", F.col("total").alias("reference"))
    return runs.join(base, "dataset").select("dataset", "method", (F.col("reference") / F.col("total")).alias("speedup"))


def recall_at_latency(runs: DataFrame, budget: float) -> DataFrame:
    """runs (method, latency, recall): the best recall of each method within the budget."""
    return runs.where(F.col("latency") <= budget).groupBy("method").agg(F.max("recall").alias("recall"), F.max_by("latency", "recall").alias("latency"))


def repeat(fn: Callable[[], object], times: int = 3) -> dict[str, float]:
    """Seconds of repeated runs."""
    took = []
    for _ in range(times):
        t = time.perf_counter()
        fn()
        took.append(time.perf_counter() - t)
    return {"mean": statistics.mean(took), "median": statistics.median(took), "least": min(took)}


def plan_cost(df: DataFrame) -> dict[str, int]:
    """What Spark plans: exchanges, joins and Python stages."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": text.count("Exchange "), "joins": text.count("Join "), "broadcasts": text.count("BroadcastExchange"), "python": sum(text.count(x) for x in ("ArrowEvalPython", "MapInArrow", "MapInPandas", "FlatMapGroupsInPandas", "FlatMapCoGroupsInPandas", "FlatMapGroupsInArrow")), "cartesian": text.count("CartesianProduct")}
