"""Exact top-k by inner product with paged M-trees, searched best first.

Vectors are scaled to integers. Inner products become distances by one more coordinate: a vector x of a tree gets
sqrt(M - |x|^2), M the largest |x|^2 of its tree, a query 0; then |q' - x'|^2 = |q|^2 + M - 2 q.x, and the nearest vector is
the one with the largest product. Distances obey the triangle inequality, so an M-tree applies.

A tree holds up to `tree_rows` vectors of one task. Its leaf pages hold up to `page` vectors, formed by splitting along the two
farthest of a few vectors; every page stores its centre, covering radius, its members' distances to the centre and its own distance to the centre of
its parent node. A search visits pages in the order of their least possible distance and computes nothing for a page when
|d(q, parent) - d(parent, page)| - radius already exceeds the k-th best, nor for a member when |d(q, page) - d(page, member)| does. Bounds
are widened by a relative 1e-9, so rounding never loses a result; scores are exact integers.

Every tree answers every block of queries, and the answers merge per query; the trees are written as a table. Trees have a bounded size, so a
very common vector is spread over trees as any other rows are.

Vectors that are null, empty, or hold a null or a non-finite component take no part, neither do rows with a null id. All others do, whatever their size:
integers are kept as doubles, which hold them exactly, and products that a double could round are computed in whole Python integers. A score among the
results that a long cannot hold raises an error, as do components beyond 1e150. Vectors meet only vectors of their own length. Ties go to the smaller id. Rows that share an id
or are repeated whole are candidates each; a query leaves out only its own row (of rows repeated whole, which are alike, one), and every query
row has its answer. An empty table gives an empty result."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, prepare, table

PAGE, FAN, TREE_ROWS, QUERY_BLOCK, SLACK = 256, 16, 1 << 16, 2048, 1e-9
NODE = "tree long, dim int, node int, parent int, leaf boolean, radius double, parent_dist double, centre binary, ids binary, dists binary, rows binary, lift double"


def scaled(vector: str, scale: int = 1024) -> Column:
    """The integer vector, or null where the vector takes no part."""
    x = F.transform(vector, lambda v: v.cast("double"))
    finite = F.col(vector).isNotNull() & (F.size(vector) > 0) & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    # a double of 2^53 or more is whole already
    whole = lambda v: F.when(F.abs(v) * scale < 2.0**53, F.floor(v * scale).cast("double")).when(F.abs(v) <= 1e150, v * scale).otherwise(F.raise_error(F.lit("a component is beyond 1e150")).cast("double"))
    return F.when(F.coalesce(finite, F.lit(False)), F.transform(x, whole))


def _split(points: np.ndarray, index: np.ndarray, size: int) -> list[np.ndarray]:
    """Groups of at most size points each: halved by nearness to two far points, evenly if they coincide."""
    out, todo = [], [index]
    while todo:
        at = todo.pop()
        if len(at) <= size:
            out.append(at)
            continue
        p = points[at]
        a = p[((p - p[0]) ** 2).sum(axis=1).argmax()]
        da = ((p - a) ** 2).sum(axis=1)
        b = p[da.argmax()]
        order = np.argsort(da - ((p - b) ** 2).sum(axis=1), kind="stable")
        half = len(at) // 2
        todo += [at[order[:half]], at[order[half:]]]
    return out


def compact(x: np.ndarray) -> np.ndarray:
    """32-bit integers where they hold all values, else doubles."""
    return x.astype(np.int32) if np.abs(x).max() < 2.0**31 else x


def build(ids: np.ndarray, x: np.ndarray, tree: int, page: int = PAGE, fan: int = FAN) -> list[dict]:
    """The nodes of one tree over integer vectors; node 0 is the root, `rows` of an inner node are its children's numbers."""
    sq = (x.astype(np.float64) ** 2).sum(axis=1)
    lift = float(sq.max())
    points = np.concatenate([x.astype(np.float64), np.sqrt(np.maximum(lift - sq, 0))[:, None]], axis=1)
    level = []
    for at in _split(points, np.arange(len(ids)), page):
        centre = points[at].mean(axis=0)
        d = np.sqrt(((points[at] - centre) ** 2).sum(axis=1))
        order = np.argsort(d)
        level.append({"leaf": True, "centre": centre, "radius": float(d.max()), "ids": ids[at][order], "dists": d[order], "rows": compact(x[at][order])})
    nodes = list(level)
    while len(level) > 1:
        centres = np.stack([n["centre"] for n in level])
        upper = []
        for at in _split(centres, np.arange(len(level)), fan):
            centre = centres[at].mean(axis=0)
            d = np.sqrt(((centres[at] - centre) ** 2).sum(axis=1))
            children = [level[i] for i in at]
            for c, dist in zip(children, d, strict=True):
                c["parent_dist"] = float(dist)
            upper.append({"leaf": False, "centre": centre, "radius": float(max(dist + c["radius"] for c, dist in zip(children, d, strict=True))), "children": children})
        nodes += upper
        level = upper
    nodes.reverse()
    for i, n in enumerate(nodes):
        n["node"] = i
    for n in nodes:
        for c in n.get("children", ()):
            c["parent"] = n["node"]
    empty = np.zeros(0)
    return [{"tree": tree, "dim": x.shape[1], "node": n["node"], "parent": n.get("parent", -1), "leaf": n["leaf"], "radius": n["radius"], "parent_dist": n.get("parent_dist", 0.0), "centre": n["centre"].tobytes(), "ids": n.get("ids", empty.astype(np.int64)).tobytes(), "dists": n.get("dists", empty).tobytes(), "rows": n["rows"].tobytes() if n["leaf"] else np.array([c["node"] for c in n["children"]], np.int32).tobytes(), "lift": lift} for n in nodes]


class Tree:
    """One tree in memory, as read from its rows."""

    def __init__(self, nodes: pd.DataFrame):
        nodes = nodes.sort_values("node")
        dim = int(nodes["dim"].iloc[0])
        self.leaf, self.radius, self.parent_dist = nodes["leaf"].to_numpy(bool), nodes["radius"].to_numpy(float), nodes["parent_dist"].to_numpy(float)
        self.lift = float(nodes["lift"].iloc[0])
        self.centre = np.stack([np.frombuffer(b) for b in nodes["centre"]])
        self.ids = [np.frombuffer(b, np.int64) for b in nodes["ids"]]
        self.dists = [np.frombuffer(b) for b in nodes["dists"]]
        self.rows = [np.frombuffer(b, np.int32 if len(b) == 4 * dim * len(i) else np.float64).reshape(-1, dim).astype(np.float64) if f else np.frombuffer(b, np.int32) for b, i, f in zip(nodes["rows"], self.ids, self.leaf, strict=True)]
        self.exact_double = max((float(np.abs(r).max()) for r, f in zip(self.rows, self.leaf, strict=True) if f and r.size), default=0.0)
        self.computed = 0

    def top(self, own: int, q: np.ndarray, k: int) -> list[tuple[int, int, bool]]:
        """The k largest (product, id, twin), ties to the smaller id; twin: the row has the id own and equals q. Products are exact Python integers."""
        point = np.append(q.astype(np.float64), 0.0)
        norm = float((point**2).sum()) + self.lift
        largest = float(np.abs(point).max()) * self.exact_double * len(q)
        kind = np.int64 if largest < 2.0**62 else object
        whole = q.astype(np.int64) if kind is np.int64 else np.array([int(c) for c in q], object)
        best_p, best_id, best_twin = np.zeros(0, kind), np.zeros(0, np.int64), np.zeros(0, bool)
        reach = np.inf  # distance of the k-th best
        d0 = float(np.sqrt(((self.centre[0] - point) ** 2).sum()))
        heap = [(max(0.0, d0 - self.radius[0]), 0, d0)]
        while heap:
            least, node, d = heapq.heappop(heap)
            if least > reach * (1 + SLACK) + SLACK:
                break
            if self.leaf[node]:
                lo, hi = np.searchsorted(self.dists[node], [d - reach * (1 + SLACK) - SLACK, d + reach * (1 + SLACK) + SLACK]) if np.isfinite(reach) else (0, len(self.dists[node]))
                hi = max(hi, lo)
                rows, ids = self.rows[node][lo:hi], self.ids[node][lo:hi]
                self.computed += len(ids)
                if largest < 2.0**53:
                    product = (rows @ point[:-1]).astype(np.int64)
                elif kind is np.int64:
                    product = rows.astype(np.int64) @ whole
                else:
                    product = np.array([sum(int(c) * w for c, w in zip(r, whole, strict=True)) for r in rows], object)
                twin = np.zeros(len(ids), bool)
                same = np.flatnonzero(ids == own)
                twin[same] = (rows[same] == point[:-1]).all(axis=1)
                p, i, w = np.concatenate([best_p, product]), np.concatenate([best_id, ids]), np.concatenate([best_twin, twin])
                order = np.array(sorted(range(len(p)), key=lambda x: (-p[x], i[x])), np.int64)[:k] if kind is object else np.lexsort((i, -p))[:k]
                best_p, best_id, best_twin = p[order], i[order], w[order]
                if len(best_p) == k:
                    reach = float(np.sqrt(max(norm - 2.0 * float(best_p[-1]), 0.0)))
                    reach += 1e-6 * max(norm, 1.0) ** 0.5
            else:
                children = self.rows[node]
                bound = reach * (1 + SLACK) + SLACK
                children = children[np.abs(d - self.parent_dist[children]) - self.radius[children] <= bound]
                self.computed += len(children)
                ds = np.sqrt(((self.centre[children] - point) ** 2).sum(axis=1))
                for c, dist in zip(children.tolist(), ds.tolist(), strict=True):
                    if dist - self.radius[c] <= bound:
                        heapq.heappush(heap, (max(0.0, dist - self.radius[c]), c, dist))
        return list(zip(best_p.tolist(), best_id.tolist(), best_twin.tolist(), strict=True))


def index(vectors: DataFrame, id_col: str, vector: str) -> DataFrame:
    """The table of trees over all rows that take part."""
    prepare(vectors.sparkSession)
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), scaled(vector).alias("v")).where("id is not null and v is not null")

    def grow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        serial, part = 0, TaskContext.get().partitionId()

        def done(dim: int) -> Iterator[pa.RecordBatch]:
            nonlocal serial
            parts = held.pop(dim)
            nodes = pd.DataFrame(build(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]), (part << 32) + serial))
            serial += 1
            for i in range(0, len(nodes), 64):
                yield pa.RecordBatch.from_pandas(nodes[i : i + 64].astype({"dim": np.int32, "node": np.int32, "parent": np.int32}), preserve_index=False)

        for b in batches:
            v = b["v"]
            size = np.diff(v.offsets.to_numpy())
            values, ids = v.flatten().to_numpy(), b["id"].to_numpy()
            starts = np.concatenate([[0], np.cumsum(size)])
            for dim in np.unique(size):
                at = np.flatnonzero(size == dim)
                held.setdefault(int(dim), []).append((ids[at], values[starts[at][:, None] + np.arange(dim)]))
                if sum(len(p[0]) for p in held[int(dim)]) >= TREE_ROWS:
                    yield from done(int(dim))
        for dim in sorted(held):
            yield from done(dim)

    return materialize(rows.mapInArrow(grow, NODE), "mtree")


def search(trees: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """queries: (query_id long, v array<double>), ids of the indexed table. Returns (query_id, rank, vec_id, score) for every query row."""
    heads = trees.where("node = 0").select(F.col("tree").alias("of_tree"), "dim")
    # rows repeated whole are asked once; the query is named by its id and vector
    asked = queries.groupBy("query_id", "v").agg(F.count("*").alias("copies"))
    asked = materialize(asked.select("query_id", "v", "copies", F.size("v").alias("dim"), F.monotonically_increasing_id().alias("q")), "mtree-queries")
    n = F.pmod(F.xxhash64("q"), F.lit(max(1, -(-asked.count() // QUERY_BLOCK)))).cast("int")
    asked = asked.withColumn("block", n)
    blocks = asked.select("dim", F.col("block").alias("of_block")).distinct()
    sent = asked.join(heads, "dim").select("of_tree", "block", "q", "query_id", "v")  # every query goes to every tree: a query set against all rows, in blocks
    pages = trees.join(blocks, "dim")

    def answer(key: tuple, nodes: pd.DataFrame, asks: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple] = []
        if len(nodes) and len(asks):
            tree = Tree(nodes)
            for q, own, v in zip(asks["q"], asks["query_id"], asks["v"], strict=True):
                # one more than k, as the query's own row may be among them
                out += [(q, i, float(p), str(p), w) for p, i, w in tree.top(own, np.asarray(v, np.float64), k + 1)]
        return pd.DataFrame(out, columns=["q", "vec_id", "near", "score", "twin"])

    found = pages.groupBy("tree", "of_block").cogroup(sent.groupBy("of_tree", "block")).applyInPandas(answer, "q long, vec_id long, near double, score string, twin boolean")
    # exact order: decimals hold what a long or a double of 2^53 cannot; scores beyond both only need their place, which the double gives
    exact = F.col("score").try_cast("decimal(38,0)")
    found = found.withColumns({"s": -F.col("near"), "e": -exact})
    place = F.row_number().over(Window.partitionBy("q").orderBy("s", "e", "vec_id", "twin"))  # limited in each task before the rows move
    best = found.withColumn("place", place).where(F.col("place") <= k + 1).groupBy("q").agg(F.sort_array(F.collect_list(F.struct("place", "vec_id", "twin", "score"))).alias("all"))
    own = F.array_position(F.transform("all", lambda x: x["twin"]), True)
    rest = F.filter("all", lambda x, i: (own == 0) | (i != own - 1))
    out = best.join(asked.select("q", "query_id", "copies"), "q").select("query_id", "copies", F.posexplode(F.slice(rest, 1, k)).alias("pos", "x"))
    out = out.select("query_id", F.explode(F.sequence(F.lit(1).cast("long"), "copies")).alias("_"), (F.col("pos") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"), F.col("x.score").alias("s"))
    score = F.coalesce(F.col("s").try_cast("long"), F.raise_error(F.concat(F.lit("a score does not fit a long: "), "s")).cast("long"))
    return out.select("query_id", "rank", "vec_id", score.alias("score"))


def op6_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    queries = vectors.where("vec_id % 100 = 0").select(F.col("vec_id").alias("query_id"), scaled("embedding").alias("v")).where("query_id is not null and v is not null")
    return search(index(vectors, "vec_id", "embedding"), queries)


SQL = """
WITH v AS (SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (SELECT q.r, q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.r <> c.r AND len(q.v) = len(c.v) WHERE q.vec_id % 100 = 0),
ranked AS (SELECT *, row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) AS rank FROM scored)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM ranked WHERE rank <= 10
"""
