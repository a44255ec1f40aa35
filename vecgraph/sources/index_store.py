"""The index on disk: vectors, adjacency by segment, the codec's model, and a manifest.

Segments are immutable; writing a segment again replaces only its partition. The manifest lists what is complete and is written last, so a reader never sees half an index."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.codecs import CODECS, ExactCodec
from ..operators.search import Index


def _plain(x: object) -> object:
    if isinstance(x, np.ndarray):
        return {"array": x.tolist(), "dtype": str(x.dtype), "shape": list(x.shape)}
    if isinstance(x, np.generic):
        return x.item()
    if isinstance(x, ExactCodec):
        return {"codec": x.name, "state": {k: _plain(v) for k, v in vars(x).items()}}
    if isinstance(x, list | tuple):
        return [_plain(v) for v in x]
    return x


def _rich(x: object) -> object:
    if isinstance(x, dict) and "array" in x:
        return np.array(x["array"], dtype=x["dtype"]).reshape(x["shape"])
    if isinstance(x, dict) and "codec" in x:
        out = CODECS[x["codec"]].__new__(CODECS[x["codec"]])
        for k, v in x["state"].items():
            setattr(out, k, _rich(v))
        return out
    if isinstance(x, list):
        return [_rich(v) for v in x]
    return x


def codec_to_json(codec: ExactCodec) -> str:
    return json.dumps(_plain(codec))


def codec_from_json(text: str) -> ExactCodec:
    return _rich(json.loads(text))


def _put(spark: SparkSession, path: str, value: dict | str) -> None:
    text = value if isinstance(value, str) else json.dumps(value)
    spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(path)


def _get(spark: SparkSession, path: str) -> str:
    return "".join(r[0] for r in spark.read.option("wholetext", True).text(path).collect())


def save_index(index: Index, path: str) -> None:
    spark = index.vectors.sparkSession
    index.vectors.write.mode("overwrite").parquet(f"{path}/vectors")
    write_segments(index.adjacency, path)
    _put(spark, f"{path}/model", codec_to_json(index.codec))
    _put(spark, f"{path}/manifest", {"segments": index.segments, "degree": index.degree, "batches": []})


def write_segments(adjacency: DataFrame, path: str) -> None:
    """Only the partitions of the segments in adjacency are replaced."""
    adjacency.repartition("segment").sortWithinPartitions("layer", "src").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("segment").parquet(f"{path}/adjacency")


def load_index(spark: SparkSession, path: str) -> Index:
    m = json.loads(_get(spark, f"{path}/manifest"))
    adjacency = spark.read.parquet(f"{path}/adjacency").withColumn("segment", F.col("segment").cast("int"))
    return Index(spark.read.parquet(f"{path}/vectors"), codec_from_json(_get(spark, f"{path}/model")), adjacency, m["segments"], m["degree"])


def bucketed(vectors: DataFrame, name: str, buckets: int = 16) -> DataFrame:
    """The vectors as a table bucketed by id, so that measuring candidates again joins without moving them."""
    vectors.write.mode("overwrite").bucketBy(buckets, "vec_id").sortBy("vec_id").saveAsTable(name)
    return vectors.sparkSession.table(name)
