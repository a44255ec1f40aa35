"""DuckDB texts of the queries: fragments and builders."""

from __future__ import annotations

EMB = "SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS vec, label FROM embeddings"


def sq(a: str, b: str, p: str = "p") -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda {p}: ({p}[1] - {p}[2]) * ({p}[1] - {p}[2])))"


def dot(a: str, b: str, p: str = "p") -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda {p}: {p}[1] * {p}[2]))"


def sub(a: str, b: str, p: str = "p") -> str:
    return f"list_transform(list_zip({a}, {b}), lambda {p}: {p}[1] - {p}[2])"


def margin(u: str, v: str, w: str) -> str:
    return f"({dot(sub(w, v), u, 'z')} - ({dot(w, w)} - {dot(v, v)}) / 2)"


def knn(k: int, base: str = "vec_id % 10 <> 0", queries: str = "vec_id % 10 = 0", name: str = "near") -> str:
    """CTEs emb and `name` (query_id, rank, vec_id, dist)."""
    return f"""emb AS ({EMB}),
{name} AS (SELECT query_id, rank, vec_id, dist FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS INTEGER) AS rank FROM (
  SELECT q.vec_id AS query_id, b.vec_id AS vec_id, sqrt({sq('q.vec', 'b.vec')}) AS dist FROM (FROM emb WHERE {queries}) q JOIN (FROM emb WHERE {base}) b ON q.vec_id <> b.vec_id)) WHERE rank <= {k})"""


def scalar(bits: int) -> str:
    """CTEs ranges (dim, lo, hi), sqc (vec_id, code, decoded) over emb."""
    top = 2**bits - 1
    return f"""flat AS (SELECT vec_id, generate_subscripts(vec, 1) - 1 AS dim, unnest(vec) AS x FROM emb),
ranges AS (SELECT dim, min(x) AS lo, max(x) AS hi FROM flat GROUP BY dim),
levels AS (SELECT vec_id, dim, x, lo, (hi - lo) / {top} AS step FROM flat JOIN ranges USING (dim)),
coded AS (SELECT vec_id, dim, x, lo, step, CASE WHEN step > 0 THEN greatest(least(floor((x - lo) / step + 0.5), {top}), 0) ELSE 0 END AS c FROM levels),
sqc AS (SELECT vec_id, list(CAST(c AS INTEGER) ORDER BY dim) AS code, list(lo + c * step ORDER BY dim) AS decoded, list(step ORDER BY dim) AS steps FROM coded GROUP BY vec_id)"""


def product(m: int, bits: int, iters: int, dim: int = 64, source: str = "emb") -> str:
    """CTEs sub (vec_id, m, x), books (m, code, c), pqc (vec_id, m, code, x) by deterministic Lloyd steps."""
    k = 1 << bits
    q, r = divmod(dim, m)
    cuts = [0]
    for i in range(m):
        cuts.append(cuts[-1] + q + (i < r))
    parts = " UNION ALL ".join(f"SELECT vec_id, {i} AS m, vec[{cuts[i] + 1}:{cuts[i + 1]}] AS x FROM {source}" for i in range(m))
    out = [f"sub AS ({parts})", f"c0 AS (SELECT m, CAST(r AS INTEGER) AS code, x AS c FROM (SELECT *, row_number() OVER (PARTITION BY m ORDER BY vec_id) - 1 AS r FROM sub) WHERE r < {k})"]
    assign = lambda c: f"SELECT vec_id, s.m AS m, any_value(s.x) AS x, min(struct_pack(d := {sq('s.x', 'c.c')}, c := c.code)).c AS code FROM sub s JOIN {c} c ON s.m = c.m GROUP BY vec_id, s.m"
    for i in range(iters):
        out.append(f"a{i} AS MATERIALIZED ({assign(f'c{i}')})")
        out.append(f"n{i} AS (SELECT m, code, j, CAST(sum(CAST(floor(x * 1073741824.0) AS BIGINT)) AS DOUBLE) / (CAST(count(*) AS DOUBLE) * 1073741824.0) AS v FROM (SELECT m, code, generate_subscripts(x, 1) AS j, unnest(x) AS x FROM a{i}) GROUP BY m, code, j)")
        out.append(f"c{i + 1} AS MATERIALIZED (SELECT o.m, o.code, coalesce(n.c, o.c) AS c FROM c{i} o LEFT JOIN (SELECT m, code, list(v ORDER BY j) AS c FROM n{i} GROUP BY m, code) n ON o.m = n.m AND o.code = n.code)")
    out.append(f"books AS (SELECT * FROM c{iters})")
    out.append(f"pqc AS MATERIALIZED ({assign('books')})")
    return ",\n".join(out)


DECODED_PQ = "pqd AS (SELECT vec_id, flatten(list(b.c ORDER BY p.m)) AS decoded FROM pqc p JOIN books b ON p.m = b.m AND p.code = b.code GROUP BY vec_id)"


def triples(size: int = 200, pair: tuple[int, int] = (1, 2)) -> str:
    """CTEs emb, picked, near, tri (u, v, w, uv, vv, wv)."""
    return f"""emb AS ({EMB}),
picked AS (SELECT * FROM emb ORDER BY (vec_id % 2147483648 * 2654435761 + 42) % 4294967296, vec_id LIMIT {size}),
near AS (SELECT query_id, rank, vec_id FROM (SELECT query_id, vec_id, row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id) AS rank FROM (
  SELECT q.vec_id AS query_id, b.vec_id AS vec_id, {sq('q.vec', 'b.vec')} AS dist FROM picked q JOIN emb b ON q.vec_id <> b.vec_id)) WHERE rank <= {max(pair)}),
tri AS (SELECT a.query_id AS u, a.vec_id AS v, b.vec_id AS w, x.vec AS uv, y.vec AS vv, z.vec AS wv FROM near a JOIN near b ON a.query_id = b.query_id AND a.rank = {pair[0]} AND b.rank = {pair[1]}
  JOIN emb x ON x.vec_id = a.query_id JOIN emb y ON y.vec_id = a.vec_id JOIN emb z ON z.vec_id = b.vec_id)"""


def select_fold(cands: str, degree: int, tau: float = 0.0) -> str:
    """Neighbour selection over a list of (d, id, v), d a squared distance, in order."""
    near = f"sqrt({sq('s.v', 'x.v')}) < sqrt(x.d) - {3 * tau}" if tau else f"{sq('s.v', 'x.v')} < x.d"
    return f"list_reduce({cands}, lambda acc, x: CASE WHEN len(acc) < {degree} AND len(list_filter(acc, lambda s: {near})) = 0 THEN list_append(acc, x) ELSE acc END, list_filter({cands}, lambda y: false))"


def selection(candidates: int, degree: int, tau: float = 0.0) -> str:
    """CTEs emb, lists (src, c), kept (src, nbrs)."""
    return f"""emb AS ({EMB}),
pairs AS (SELECT a.vec_id AS src, b.vec_id AS id, {sq('a.vec', 'b.vec')} AS d, b.vec AS v FROM emb a JOIN emb b ON a.vec_id <> b.vec_id),
lists AS (SELECT src, list(struct_pack(d := d, id := id, v := v) ORDER BY d, id) AS c FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY d, id) AS r FROM pairs) WHERE r <= {candidates} GROUP BY src),
kept AS MATERIALIZED (SELECT src, {select_fold('c', degree, tau)} AS nbrs FROM lists)"""


def bulk(candidates: int, degree: int, tau: float = 0.0) -> str:
    """CTEs of selection, and graph (src, nbrs) with reverse edges."""
    return selection(candidates, degree, tau) + f""",
e AS (SELECT src, unnest(nbrs) AS n FROM kept),
bothw AS (SELECT src, n.id AS dst FROM e UNION SELECT n.id, src FROM e),
joint AS (SELECT b.src, list(struct_pack(d := {sq('x.vec', 'y.vec')}, id := b.dst, v := y.vec) ORDER BY {sq('x.vec', 'y.vec')}, b.dst) AS c FROM bothw b JOIN emb x ON x.vec_id = b.src JOIN emb y ON y.vec_id = b.dst GROUP BY b.src),
graph AS MATERIALIZED (SELECT src, CASE WHEN len(c) <= {degree} THEN c ELSE {select_fold('c', degree, tau)} END AS nbrs FROM joint),
edges AS (SELECT src, generate_subscripts(nbrs, 1) AS rank, unnest(nbrs) AS n FROM graph)"""


def ordered_axes(dims: int) -> str:
    """CTEs emb, turned (vec_id, vec): the dims dimensions of largest variance, in that order."""
    return f"""emb AS ({EMB}),
axes AS (SELECT list(dim ORDER BY f DESC, dim)[1:{dims}] AS ax FROM (SELECT dim, floor((avg(x * x) - avg(x) * avg(x)) * 1048576) AS f FROM (SELECT generate_subscripts(vec, 1) AS dim, unnest(vec) AS x FROM emb) GROUP BY dim)),
turned AS MATERIALIZED (SELECT vec_id, list_transform(ax, lambda i: vec[i]) AS vec FROM emb, axes)"""


def aligned(m: int, dims: int, iters: int, h: int = 8) -> str:
    """CTEs of ordered_axes and product over them, sdt, span (lo, rng), adtq (vec_id, m, code, d, qd), sdtq."""
    top = 2**h - 1
    level = lambda d: f"CASE WHEN rng <= 0 THEN 0 ELSE CAST(greatest(least(floor(({d} - lo) / rng * {top}), {top}), 0) AS INTEGER) END"
    return ordered_axes(dims) + ",\n" + product(m, 4, iters, dims, "turned") + f""",
sdt AS (SELECT a.m, a.code AS a, b.code AS b, {sq('a.c', 'b.c')} AS d FROM books a JOIN books b ON a.m = b.m),
adt AS MATERIALIZED (SELECT vec_id, s.m, b.code, {sq('s.x', 'b.c')} AS d FROM sub s JOIN books b ON s.m = b.m),
tops AS (SELECT m, max(d) AS hi, min(d) AS lo FROM (SELECT m, d FROM adt UNION ALL SELECT m, d FROM sdt) GROUP BY m),
span AS (SELECT min(lo) AS lo, sum(hi) - min(lo) AS rng FROM tops),
adtq AS (SELECT vec_id, m, code, d, {level('d')} AS qd FROM adt, span),
sdtq AS (SELECT m, a, b, d, {level('d')} AS qd FROM sdt, span)"""


def trigrams(table: str, id_col: str, text: str, dim: int = 256) -> str:
    """CTEs tri_n (id, slot, n), tvec (vec_id, vec)."""
    return f"""codes AS (SELECT {id_col} AS id, list_transform(string_split(lower({text}), ''), lambda c: CAST(unicode(c) AS BIGINT)) AS c FROM {table} WHERE length({text}) >= 3),
hashed AS (SELECT id, unnest(list_transform(range(1, len(c) - 1), lambda i: (c[i] * 961 + c[i + 1] * 31 + c[i + 2]) % {dim})) AS slot FROM codes),
tri_n AS (SELECT id, slot, count(*) AS n FROM hashed GROUP BY id, slot),
norms AS (SELECT id, sqrt(CAST(sum(n * n) AS DOUBLE)) AS z FROM tri_n GROUP BY id),
cells AS (SELECT o.id, s.slot, coalesce(t.n, 0) / o.z AS x FROM norms o CROSS JOIN (SELECT unnest(range({dim})) AS slot) s LEFT JOIN tri_n t ON t.id = o.id AND t.slot = s.slot),
tvec AS MATERIALIZED (SELECT id AS vec_id, list(x ORDER BY slot) AS vec FROM cells GROUP BY id)"""
