"""User-defined functions beyond Columns: a grouped aggregate, a table function, and a scalar look-up in Arrow batches."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


@F.pandas_udf("array<long>")
def topk_agg(ids: pd.Series, dist: pd.Series) -> list:
    """The ten nearest ids of a group, ties to the smaller. For groups of bounded size; top_k() in operators.exact has no such bound."""
    order = np.lexsort((ids.to_numpy(), dist.to_numpy()))[:10]
    return ids.to_numpy()[order].tolist()


@F.pandas_udf("array<double>")
def centroid_agg(vec: pd.Series) -> list:
    """The mean vector of a group, from sums in fixed point, so that it does not depend on the order of rows. For groups that fit a task; codecs sum in every task first."""
    x = np.floor(np.stack(vec.to_numpy()) * (1 << 30)).astype(np.int64)
    return (x.sum(axis=0) / (len(x) * float(1 << 30))).tolist()


@F.pandas_udf("array<double>")
def gram_agg(vec: pd.Series) -> list:
    """The upper triangle, row by row, of the sum of outer products of a group's vectors."""
    x = np.stack(vec.to_numpy())
    return (x.T @ x)[np.triu_indices(x.shape[1])].tolist()


@F.udtf(returnType="vec_id: long, dim: int, x: double")
class ExplodeDims:
    """SELECT * FROM explode_dims(TABLE(v)): one row for each component."""

    def eval(self, row):
        for i, x in enumerate(row["vec"]):
            yield row["vec_id"], i, x


def register_udfs(spark: SparkSession) -> None:
    spark.udtf.register("explode_dims", ExplodeDims)
    for name, f in (("topk_agg", topk_agg), ("centroid_agg", centroid_agg), ("gram_agg", gram_agg)):
        spark.udf.register(name, f)


@F.arrow_udf("double")
def _adc(table: pa.Array, code: pa.Array) -> pa.Array:
    t, c = (x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1) for x in (table, code))
    if not len(t):
        return pa.array([], pa.float64())
    k = t.shape[1] // c.shape[1]
    return pa.array(np.take_along_axis(t, c + np.arange(c.shape[1]) * k, axis=1).sum(axis=1))


def adc_distance(table: Column | str, code: Column | str) -> Column:
    """Sum of the looked-up entries of a flat table (subspaces x centroids) for a code."""
    return _adc(table, code)
