"""Numpy kernels of graph construction and search. Many insertions or queries advance together, so that interpreter time is shared.

A distance source answers `state(points)` for the vectors being inserted or searched, `of(state, ids)` for distances from each of them to vertices, and
`pair(a, b)` for distances among vertices. Distances are squared, or small integers that stand for them. Vertex -1 is padding."""

from __future__ import annotations

from collections import Counter

import numpy as np

FAR = np.float32(np.inf)
CACHED_BYTES = 1 << 19  # of differences at once
BEAM_ROWS = 256


def fold_sq(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """(len(q), len(x)) squared distances whose sums fold over the dimensions from left to right."""
    out = np.zeros((len(q), len(x)))
    for d in range(q.shape[1]):
        diff = q[:, d, None] - x[None, :, d]
        out += diff * diff
    return out


class Points:
    """Distances between points: full vectors, rotated ones, or integers weighted by dimension."""

    def __init__(self, x: np.ndarray, weight: np.ndarray | None = None):
        self.x, self.weight, self.n = x, weight, len(x)
        self.scale = None if weight is None else np.sqrt(weight)

    def state(self, points: np.ndarray) -> np.ndarray:
        return points

    def own(self, at: np.ndarray) -> np.ndarray:
        return self.x[at]

    def _sum(self, diff: np.ndarray) -> np.ndarray:
        if self.weight is None:
            return np.einsum("...d,...d->...", diff, diff)
        diff = diff.astype(np.float32)
        diff *= self.scale
        return np.einsum("...d,...d->...", diff, diff)

    def of(self, state: np.ndarray, ids: np.ndarray) -> np.ndarray:
        return self.some(state, np.repeat(np.arange(len(ids)), ids.shape[1]), ids.ravel()).reshape(ids.shape)

    def some(self, state: np.ndarray, rows: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Distances of the given rows of state, each to one vertex, in pieces that stay in the cache."""
        step = max(1, CACHED_BYTES // (self.x.itemsize * max(1, self.x.shape[1])))
        parts = []
        for s in range(0, max(1, len(ids)), step):
            diff = self.x.take(ids[s : s + step], axis=0, mode="wrap")
            own = state.take(rows[s : s + step], axis=0)
            parts.append(self._sum(np.subtract(diff, own, out=diff) if diff.dtype == own.dtype else diff - own))
        return parts[0] if len(parts) == 1 else np.concatenate(parts)

    def pair(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return self._sum(self.x[b] - self.x[a][:, None, :])

    def pairs(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Distances of vertices, one to one."""
        return self.some(self.x, a, b)

    def among(self, at: np.ndarray, state: np.ndarray) -> np.ndarray:
        """Distances of vertices (with their state) to each other: the same in both directions."""
        out = np.zeros((len(at), len(at)))
        r, c = np.triu_indices(len(at), 1)
        out[r, c] = out[c, r] = self.pairs(at[r], at[c])
        return out


class LazyTables:
    """Tables of vectors, computed when asked for: those of 8-bit product codes take 1 kB for each subspace, many times their vector."""

    def __init__(self, codec, x: np.ndarray):
        self.codec, self.x = codec, x

    def __getitem__(self, at: np.ndarray) -> np.ndarray:
        at = np.asarray(at)
        got = self.codec.table_rows(self.x[at.ravel()])
        return got.reshape(*at.shape, *got.shape[1:])


class Tables:
    """Distances by table look-up over codes: one table for each inserted vector (subspaces x centroids) and one centroid-to-centroid table
    that all share. `wide` is the type of sums. Codes are kept with the offset of their subspace, so a look-up is one take."""

    def __init__(self, codes: np.ndarray, tables: np.ndarray | None, between: np.ndarray, wide: type = np.float32, block: int = 0):
        self.n, self.m = codes.shape
        self.k = between.shape[1]
        self.tables, self.wide, self.block = tables, wide, block
        self.offset = codes.astype(np.int32) + np.arange(self.m, dtype=np.int32) * self.k
        self.between = np.ascontiguousarray(between.reshape(self.m * self.k, self.k))
        self.codes = codes

    def state(self, tables: np.ndarray) -> np.ndarray:
        return tables

    def own(self, at: np.ndarray) -> np.ndarray:
        if self.tables is not None:
            return self.tables[at]
        return self.between[self.offset[at]]

    def look_up(self, state: np.ndarray, offset: np.ndarray) -> np.ndarray:
        flat = state.reshape(len(state), -1)
        base = (np.arange(len(state), dtype=np.int64) * flat.shape[1]).reshape(-1, *([1] * (offset.ndim - 1)))
        if not self.block:
            return flat.ravel().take(offset + base).sum(axis=-1, dtype=self.wide)
        total = np.zeros(offset.shape[:-1], self.wide)  # as a register of `block` tables works: some subspaces at a time
        for s in range(0, self.m, self.block):
            total += flat.ravel().take(offset[..., s : s + self.block] + base).sum(axis=-1, dtype=self.wide)
        return total

    def of(self, state: np.ndarray, ids: np.ndarray) -> np.ndarray:
        return self.look_up(state, self.offset[ids])

    def summed(self, state: np.ndarray, rows: np.ndarray, offset: np.ndarray) -> np.ndarray:
        """Sums of the given rows of state, each over one row of offsets."""
        flat, base = state.reshape(-1), (rows * (state.size // max(1, len(state))))[:, None]
        total = np.zeros(len(rows), self.wide)
        for s in range(0, self.m, self.block or self.m):
            total += flat.take(offset[:, s : s + (self.block or self.m)] + base).sum(axis=-1, dtype=self.wide)
        return total

    def some(self, state: np.ndarray, rows: np.ndarray, ids: np.ndarray) -> np.ndarray:
        return self.summed(state, rows, self.offset[ids])

    def among(self, at: np.ndarray, state: np.ndarray) -> np.ndarray:
        return self.of(state, np.tile(at, (len(at), 1))).astype(np.float64)

    def pairs(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return self.between.ravel().take(self.offset[a] * self.k + self.codes[b]).sum(axis=-1, dtype=self.wide)

    def pair(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        rows = self.offset[a] * self.k
        return self.between.ravel().take(rows[:, None, :] + self.codes[b]).sum(axis=-1, dtype=self.wide)


class Graph:
    """Adjacency by layer; with `inline` the neighbours' offset codes lie beside their ids and searches read nothing else."""

    def __init__(self, n: int, degrees: list[int], source: Points | Tables, inline: bool = False):
        self.adj = [np.full((n, r), -1, np.int32) for r in degrees]
        self.source = source
        self.inline = [np.zeros((n, r, source.m), np.int32) for r in degrees] if inline and isinstance(source, Tables) else None
        self.entry, self.top = -1, -1
        self.count: Counter = Counter()

    def set(self, layer: int, at: np.ndarray, lists: np.ndarray) -> None:
        self.adj[layer][at] = lists
        if self.inline is not None:
            self.inline[layer][at] = self.source.offset[lists]

    def near(self, layer: int, at: np.ndarray, state: np.ndarray, rows: np.ndarray, ids: np.ndarray, fresh: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        """Distances of the given rows of state to those entries (row, column) of the neighbours `ids` of `at` that are fresh."""
        r, c = fresh
        if self.inline is not None:
            self.count["block_fetches"] += len(at)
            return self.source.summed(state, rows[r], self.inline[layer][at[r], c])
        self.count["vector_fetches"] += int((ids >= 0).sum())
        return self.source.some(state, rows[r], ids[r, c])


def beam(graph: Graph, layer: int, state: np.ndarray, entry: np.ndarray, width: int, window: int = 0, measure=None) -> tuple[np.ndarray, np.ndarray]:
    """Best-first search of each row of state with a bounded candidate set: ids and distances by rising distance. It stops when every candidate
    in the set is expanded; with `window`, also when the median of the last so many expanded distances exceeds the farthest candidate held (relaxed monotonic stop).
    `measure(rows, ids, bound)` may replace the distance of candidates (early abort)."""
    if len(state) > BEAM_ROWS and measure is None:  # rows walk apart, so that what a step touches stays in the cache
        parts = [beam(graph, layer, state[s : s + BEAM_ROWS], entry[s : s + BEAM_ROWS], width, window) for s in range(0, len(state), BEAM_ROWS)]
        return tuple(np.concatenate(y) for y in zip(*parts, strict=True))
    b, n = len(state), graph.source.n + 1
    ids, dist = np.full((b, width), -1, np.int64), np.full((b, width), np.inf)
    open_ = np.full((b, width), np.inf)  # distances of candidates that are not expanded
    seen = np.zeros(b * n, bool)
    seen[::n] = True  # stands for padding
    rows = np.arange(b)
    ids[:, 0] = entry
    dist[:, 0] = graph.source.of(state, entry[:, None])[:, 0] if measure is None else measure(rows, entry[:, None], np.full(b, np.inf))[:, 0]
    open_[:, 0] = dist[:, 0]
    seen[rows * n + 1 + entry] = True
    trail = np.full((b, window), np.nan) if window else None
    live, hops = rows, 0
    while len(live):
        now = open_ if len(live) == b else open_[live]
        pick = now.argmin(axis=1)
        best = now[rows[: len(live)], pick]
        go = np.isfinite(best)
        if window:
            trail[live, hops % window] = best
            if hops >= window:
                go &= ~(np.median(trail[live], axis=1) > np.where(np.isfinite(dist[live, -1]), dist[live, -1], np.inf))
        if not go.all():
            live, pick = live[go], pick[go]
        if not len(live):
            break
        hops += 1
        graph.count["hops"] += len(live)
        open_[live, pick] = np.inf
        at = ids[live, pick]
        nb = graph.adj[layer][at].astype(np.int64)
        cell = nb + (live * n + 1)[:, None]
        r, c = np.nonzero(~seen[cell])
        seen[cell[r, c]] = True
        graph.count["distances"] += len(r)
        if measure is None:
            new = graph.near(layer, at, state, live, nb, (r, c)).astype(np.float64)
        else:
            new = measure(live, nb, dist[live, -1])[r, c]
        better = new < dist[live[r], -1]  # the others stay behind all that is held
        r, new, v = r[better], new[better], nb[r[better], c[better]]
        if not len(r):
            continue
        n_new = np.bincount(r, minlength=len(live))
        some = np.flatnonzero(n_new)
        held, most = live[some], int(n_new.max())
        to = np.repeat(np.arange(len(some)), n_new[some]) * (width + most) + width + np.arange(len(r)) - np.repeat(np.cumsum(n_new[some]) - n_new[some], n_new[some])
        wide = []
        for old, fresh, empty in ((dist, new, np.inf), (ids, v, -1), (open_, new, np.inf)):
            both = np.full((len(some), width + most), empty, old.dtype)
            both[:, :width] = old[held]
            both.reshape(-1)[to] = fresh
            wide.append(both)
        order = np.argsort(wide[0], axis=1, kind="stable")[:, :width] + (np.arange(len(some)) * (width + most))[:, None]
        dist[held], ids[held], open_[held] = (y.reshape(-1).take(order) for y in wide)
    return ids, dist


def select_lists(source: Points | Tables, ids: np.ndarray, dist: np.ndarray, degree: int, tau: float = 0.0, count: Counter | None = None) -> np.ndarray:
    """Neighbour selection for many vertices: ids and dist are candidate lists by rising distance. A candidate goes if a kept one is strictly
    nearer to it than the vertex is (by more than 3 tau in true distance). Returns (rows, degree), padded with -1."""
    b, c = ids.shape
    kept, size = np.full((b, degree), -1, np.int64), np.zeros(b, np.int64)
    for j in range(c):
        live = np.flatnonzero((ids[:, j] >= 0) & (size < degree) & np.isfinite(dist[:, j]))
        if not len(live):
            if (size >= degree).all():
                break
            continue
        some = int(size[live].max())
        own = ids[live, j]
        if some:
            others = kept[live, :some]
            r, at = np.nonzero(others >= 0)
            d = source.pairs(own[r], others[r, at]).astype(np.float64)
            if count is not None:
                count["selection_distances"] += len(r)
            limit = dist[live, j][r]
            near = np.sqrt(d) < np.sqrt(limit) - 3 * tau if tau else d < limit
            live = live[np.bincount(r[near], minlength=len(live)) == 0]
        kept[live, size[live]] = ids[live, j]
        size[live] += 1
    return kept


def without_mutual(graph: Graph, layer: int, x: np.ndarray, lists: np.ndarray) -> np.ndarray:
    """The lists without neighbours that have x in their own list: those edges are there already."""
    out = lists.astype(np.int64)
    for s in range(0, len(x), 4096):
        part = out[s : s + 4096]
        there = (graph.adj[layer][part] == x[s : s + 4096, None, None]).any(axis=2)
        part[there & (part >= 0)] = -1
    return out


def link_back(graph: Graph, layer: int, x: np.ndarray, lists: np.ndarray, tau: float = 0.0) -> None:
    """Reverse edges: x joins the list of each neighbour, which is selected anew where it overflows."""
    degree = graph.adj[layer].shape[1]
    row, col = np.nonzero(lists >= 0)
    if not len(row):
        return
    to, frm = lists[row, col], x[row]
    order = np.argsort(to, kind="stable")
    to, frm = to[order], frm[order]
    ys, first, n = np.unique(to, return_index=True, return_counts=True)
    have = (graph.adj[layer][ys] >= 0).sum(axis=1)
    fits = have + n <= degree
    place = have[np.searchsorted(ys, to)] + np.arange(len(to)) - first[np.searchsorted(ys, to)]  # behind what the list has
    few = fits[np.searchsorted(ys, to)]
    graph.adj[layer][to[few], place[few]] = frm[few]
    if graph.inline is not None and fits.any():
        graph.set(layer, ys[fits], graph.adj[layer][ys[fits]])
    over = np.flatnonzero(~fits)
    for s in range(0, len(over), 512):
        part = over[s : s + 512]
        width = int((have[part] + n[part]).max())
        cand = np.full((len(part), width), -1, np.int64)
        cand[:, : min(width, degree)] = graph.adj[layer][ys[part], :width]
        mine = np.arange(len(part)).repeat(n[part])
        rank = np.arange(len(mine)) - np.repeat(np.cumsum(n[part]) - n[part], n[part])
        cand[mine, have[part][mine] + rank] = frm[first[part][mine] + rank]
        d = graph.source.pair(ys[part], cand).astype(np.float64)
        graph.count["reverse_distances"] += int((cand >= 0).sum())
        d[cand < 0] = np.inf
        order = np.lexsort((cand, d), axis=1)
        graph.set(layer, ys[part], select_lists(graph.source, np.take_along_axis(cand, order, 1), np.take_along_axis(d, order, 1), degree, tau, graph.count))


def build_layered(source: Points | Tables, levels: np.ndarray, candidates: int, degree: int, base_factor: int = 2, batch: int = 256, inline: bool = False, tau: float = 0.0) -> Graph:
    """Layered graph by insertion in batches that double up to `batch`: each batch searches the graph as it stands, its members are candidates of each
    other too. batch=1 inserts one vertex after another."""
    n, top = len(levels), int(levels.max(initial=0))
    graph = Graph(n, [degree * base_factor] + [degree] * top, source, inline)
    if not n:
        return graph
    first = 0
    graph.entry, graph.top = first, int(levels[first])
    start, size = 1, 1
    while start < n:
        members = np.arange(start, min(n, start + size))
        state = source.own(members)
        entry = np.full(len(members), graph.entry, np.int64)
        plans = []
        for layer in range(top, -1, -1):
            joins = levels[members] >= layer
            ids = np.full((len(members), candidates), -1, np.int64)
            dist = np.full((len(members), candidates), np.inf)
            if layer <= graph.top:
                for rows, width in ((np.flatnonzero(~joins), 1), (np.flatnonzero(joins), candidates)):
                    if len(rows) and (width > 1 or layer > 0):
                        i, d = beam(graph, layer, state[rows], entry[rows], width)
                        ids[rows, :width], dist[rows, :width] = i, d
                        entry[rows] = np.where(i[:, 0] >= 0, i[:, 0], entry[rows])
            rows = np.flatnonzero(joins)
            if len(rows):
                mates = members[rows]
                if len(rows) > 1:
                    d = source.among(mates, state[rows])
                    graph.count["distances"] += d.size
                    np.fill_diagonal(d, np.inf)
                    cand, cd = np.concatenate([ids[rows], np.tile(mates, (len(rows), 1))], 1), np.concatenate([dist[rows], d], 1)
                    order = np.argsort(cd, axis=1, kind="stable")[:, :candidates]
                    cand, cd = np.take_along_axis(cand, order, 1), np.take_along_axis(cd, order, 1)
                else:
                    cand, cd = ids[rows], dist[rows]
                plans.append((layer, mates, select_lists(source, np.where(np.isfinite(cd), cand, -1), cd, graph.adj[layer].shape[1], tau, graph.count)))
        for layer, mates, lists in plans:
            graph.set(layer, mates, lists)
        for layer, mates, lists in plans:
            link_back(graph, layer, mates, without_mutual(graph, layer, mates, lists), tau)
        best = members[levels[members].argmax()]
        if levels[best] > graph.top:
            graph.entry, graph.top = int(best), int(levels[best])
        start += len(members)
        size = min(batch, 2 * size)
    return graph


PIECE_BYTES = 16 << 20


def to_all(source: Points | Tables, at: np.ndarray) -> np.ndarray:
    """Distances of the vertices `at` to all, in pieces whose differences or look-ups take about PIECE_BYTES."""
    width = source.x.shape[1] if hasattr(source, "x") else source.m
    step = max(1, PIECE_BYTES // (8 * width * max(1, len(at))))
    own = source.own(at)
    return np.concatenate([source.of(own, np.tile(np.arange(c, min(source.n, c + step)), (len(at), 1))) for c in range(0, source.n, step)], axis=1)


def build_bulk(source: Points | Tables, candidates: int, degree: int, tau: float = 0.0, reachable: bool = True, inline: bool = False, block: int = 256) -> Graph:
    """Single layer without insertion order: exact nearest candidates, selection, reverse edges, selection."""
    n = source.n
    graph = Graph(n, [degree], source, inline)
    if not n:
        return graph
    for s in range(0, n, block):
        at = np.arange(s, min(n, s + block))
        d = to_all(source, at).astype(np.float64)
        graph.count["distances"] += d.size
        d[np.arange(len(at)), at] = np.inf
        order = np.argsort(d, axis=1, kind="stable")[:, : min(candidates, n - 1)]
        graph.set(0, at, select_lists(source, order, np.take_along_axis(d, order, 1), degree, tau, graph.count))
    lists = graph.adj[0].astype(np.int64).copy()
    link_back(graph, 0, np.arange(n), without_mutual(graph, 0, np.arange(n), lists), tau)
    sample = np.arange(n)[:: max(1, n // 256)]
    mean = to_all(source, sample).mean(axis=0)
    graph.entry, graph.top = int(mean.argmin()), 0
    if reachable:
        ensure_reachable(graph)
    return graph


def reached(graph: Graph, layer: int = 0) -> np.ndarray:
    seen = np.zeros(graph.source.n, bool)
    front = np.array([graph.entry]) if graph.entry >= 0 else np.zeros(0, int)
    seen[front] = True
    while len(front):
        nb = graph.adj[layer][front].ravel()
        nb = np.unique(nb[nb >= 0])
        front = nb[~seen[nb]]
        seen[front] = True
    return seen


def ensure_reachable(graph: Graph) -> None:
    """Attach what the entry does not reach to the nearest reached vertex with a free place, or with an edge that the tree of first visits does not need;
    so what was reached stays reached, degrees hold, and each step reaches at least one vertex more."""
    adj = graph.adj[0]
    parent = np.full(graph.source.n, -1, np.int64)
    if graph.entry < 0:
        return
    parent[graph.entry] = graph.entry

    def visit(front: list[int]) -> None:
        while front:
            fresh = []
            for v in front:
                for y in adj[v][adj[v] >= 0].tolist():
                    if parent[y] < 0:
                        parent[y] = v
                        fresh.append(y)
            front = fresh

    visit([graph.entry])
    for x in range(graph.source.n):
        if parent[x] >= 0:
            continue
        inside = np.flatnonzero(parent >= 0)
        d = graph.source.of(graph.source.own(np.array([x])), inside[None, :])[0]
        for y in inside[np.argsort(d, kind="stable")].tolist():
            row = adj[y].copy()
            free = np.flatnonzero((row < 0) | (parent[np.maximum(row, 0)] != y))
            if len(free):
                row[free[0] if row[free[0]] < 0 else free[-1]] = x
                graph.set(0, np.array([y]), row[None, :])
                parent[x] = y
                visit([x])
                break


def descend(graph: Graph, state: np.ndarray, width: int, **how) -> tuple[np.ndarray, np.ndarray]:
    """Search: greedy through the upper layers, then a beam on the lowest."""
    entry = np.full(len(state), graph.entry, np.int64)
    for layer in range(graph.top, 0, -1):
        entry = beam(graph, layer, state, entry, 1, measure=how.get("measure"))[0][:, 0]
    return beam(graph, 0, state, entry, width, **how)


def early_abort(x: np.ndarray, q: np.ndarray, chunk: int, eps: float, count: Counter):
    """Distances of randomly rotated vectors dimension by dimension: a candidate is given up when its partial sum, scaled to all dimensions,
    exceeds (1 + eps / sqrt(read))^2 times the bound. Given-up candidates are infinitely far."""
    dim = x.shape[1]

    def measure(rows: np.ndarray, ids: np.ndarray, bound: np.ndarray) -> np.ndarray:
        total = np.zeros(ids.shape)
        alive = ids >= 0
        for s in range(0, dim, chunk):
            r, c = np.nonzero(alive)
            if not len(r):
                break
            diff = x[ids[r, c], s : s + chunk] - q[rows[r], s : s + chunk]
            count["dimensions"] += diff.size
            total[r, c] += (diff * diff).sum(axis=1)
            t = min(dim, s + chunk)
            if t < dim:
                alive &= total * (dim / t) <= ((1 + eps / np.sqrt(t)) ** 2 * bound)[:, None]
        return np.where(alive, total, np.inf)

    return measure


def lru_misses(addresses: np.ndarray, size: int = 32 << 10, line: int = 64, ways: int = 8) -> tuple[int, int]:
    """(misses, accesses) of byte addresses on a set-associative cache that replaces the least recently used line."""
    sets = size // line // ways
    lines = addresses // line
    held: dict[int, list[int]] = {}
    misses = 0
    for x in lines.tolist():
        s = held.setdefault(x % sets, [])
        if x in s:
            s.remove(x)
        else:
            misses += 1
            if len(s) == ways:
                s.pop(0)
        s.append(x)
    return misses, len(lines)
