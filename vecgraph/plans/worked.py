"""One insertion followed step by step: on seven vertices with given distances, and on the nearest vectors of a table."""

from __future__ import annotations

import numpy as np

from ..operators.kernels import select_lists

# Distances to the inserted vertex; edges of the graph; distances among vertices that matter for selection.
TO_NEW = {17: 0.20, 5: 0.25, 3: 0.30, 9: 0.35, 15: 0.45, 0: 0.49, 13: 0.54}
EDGES = {0: [5, 9, 13], 5: [15, 0], 9: [0], 15: [5, 17, 3], 17: [15], 3: [15], 13: [0]}
AMONG = {(5, 17): 0.40, (3, 17): 0.15, (9, 17): 0.15, (3, 5): 0.50, (5, 9): 0.50, (3, 9): 0.50}


class Lookup:
    """Distances by look-up; squared where the kernels ask for squares is not needed, as only their order counts."""

    def __init__(self, among: dict[tuple[int, int], float], n: int):
        self.among, self.n = among, n

    def pair(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.array([[self.among.get((min(x, y), max(x, y)), 9.0) if y >= 0 else np.inf for y in row] for x, row in zip(a.tolist(), b.tolist(), strict=True)])

    def pairs(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return self.pair(a, b[:, None])[:, 0]


def run(width: int = 4, degree: int = 2, to_new: dict = TO_NEW, edges: dict = EDGES, among: dict = AMONG, entry: int = 0) -> list[tuple[int, str, str]]:
    near = lambda v: (to_new[v], v)
    held, done, seen, out = [entry], set(), {entry}, []
    while True:
        open_ = [v for v in held if v not in done]
        if not open_:
            break
        at = min(open_, key=near)
        done.add(at)
        fresh = [v for v in edges[at] if v not in seen]
        seen |= set(fresh)
        held = sorted(held + fresh, key=near)[:width]
        out.append((len(out), f"expand {at}", ",".join(map(str, held))))
    ids, dist = np.array([held]), np.array([[to_new[v] for v in held]])
    kept = select_lists(Lookup(among, max(to_new) + 1), ids, dist, degree)[0]
    out.append((len(out), "select", ",".join(str(v) for v in kept.tolist() if v >= 0)))
    out.append((len(out), "evaluated", ",".join(map(str, sorted(seen)))))
    return out


def insertion(ids: np.ndarray, x: np.ndarray, dist: np.ndarray, links: int = 3) -> list[tuple[int, str, str]]:
    """The steps for a vector whose nearest vertices `ids`, nearest first, lie at `dist`: they form a graph in which each knows its `links` nearest, both ways, entered at the farthest."""
    between = np.sqrt(((x[:, None, :] - x[None]) ** 2).sum(axis=2))
    name = ids.tolist()
    edges: dict[int, list[int]] = {v: [] for v in name}
    for i, v in enumerate(name):
        for j in [j for j in np.argsort(between[i], kind="stable").tolist() if j != i][:links]:
            for a, b in ((v, name[j]), (name[j], v)):
                if b not in edges[a]:
                    edges[a].append(b)
    among = {(min(a, b), max(a, b)): float(between[i, j]) for i, a in enumerate(name) for j, b in enumerate(name) if i < j}
    return run(to_new=dict(zip(name, dist.tolist(), strict=True)), edges=edges, among=among, entry=name[-1])
