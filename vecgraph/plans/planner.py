"""Choice of a search plan before Spark plans it, and the search as a table function."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators import search as S
from ..operators.kernels import descend

TABLE_FUNCTION_ROWS = 200_000


@dataclass
class SearchPlan:
    kind: str
    why: str
    ef: int = 0


def choose(n: int, queries: int, k: int, selectivity: float = 1.0, ef: int = 64, degree: int = 16, has_graph: bool = True) -> SearchPlan:
    """exact for few rows or a selective predicate, graph where walks cost less than a scan of the codes, else code_scan."""
    passing = n * selectivity
    if passing <= 20 * max(k, 50) or selectivity < 0.02:
        return SearchPlan("exact", f"only {passing:.0f} rows pass")
    wide = int(ef / max(selectivity, 0.05))
    walk = wide * degree
    if has_graph and walk < passing / 4:
        return SearchPlan("graph", f"about {walk} distances a query against {passing:.0f}", wide)
    return SearchPlan("code_scan", f"a walk would touch {walk} of {passing:.0f} rows")


def register_search(spark: SparkSession, index: S.Index, name: str = "graph_search", mode_rerank: bool = True) -> None:
    """SELECT * FROM graph_search(TABLE(SELECT vec_id, vec FROM q), 10, 64): query_id, rank, vec_id, dist. For one-segment indexes of checked size: the graph is broadcast."""
    if index.segments != 1 or index.vectors.count() > TABLE_FUNCTION_ROWS:
        raise ValueError(f"the table function is for one segment of at most {TABLE_FUNCTION_ROWS} rows; use search()")
    row = index.packed(True).first().asDict(recursive=True)
    sent = spark.sparkContext.broadcast((index.codec, row))

    class GraphSearch:
        def __init__(self):
            self.asked, self.k, self.ef = [], 10, 64

        def eval(self, row, k: int, ef: int):
            self.k, self.ef = k, ef
            self.asked.append((row["vec_id"], row["vec"]))

        def terminate(self):
            if not self.asked:
                return
            codec, row = sent.value
            graph, ids = S.load_segment(codec, row, False)
            vectors = np.frombuffer(row["vecs"]).reshape(len(ids), -1)
            q = np.array([v for _, v in self.asked], np.float64)
            found, dist = descend(graph, codec.query_state(q), self.ef)
            if mode_rerank:
                dist = np.where(found >= 0, ((vectors[np.maximum(found, 0)] - q[:, None, :]) ** 2).sum(-1), np.inf)
                order = np.lexsort((found, dist), axis=1)
                found, dist = np.take_along_axis(found, order, 1), np.take_along_axis(dist, order, 1)
            for (qid, _), row, d in zip(self.asked, found.tolist(), dist.tolist(), strict=True):
                for r, (v, z) in enumerate([(v, z) for v, z in zip(row, d, strict=True) if v >= 0][: self.k]):
                    yield int(qid), r + 1, int(ids[v]), float(z) ** 0.5

    spark.udtf.register(name, udtf(GraphSearch, returnType="query_id: long, rank: int, vec_id: long, dist: double"))
