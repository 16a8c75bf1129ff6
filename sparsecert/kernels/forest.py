"""Spanning forests on numpy arrays: rounds of picking each component's first edge, then contraction.

The order of the arrays is the edges' total order, so the forest found is the one that a pass over
the edges with union-find would keep; sorted by weight it is the minimum spanning forest.
"""

from __future__ import annotations

import numpy as np


def compact(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Vertices in ascending order, and both ends as places in them."""
    ids, places = np.unique(np.concatenate([u, v]), return_inverse=True)
    return ids, places[: len(u)], places[len(u) :]


def _roots(parent: np.ndarray) -> np.ndarray:
    while True:
        up = parent[parent]
        if np.array_equal(up, parent):
            return parent
        parent = up


def forest(n: int, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the forest's edges in ascending order, and each vertex's component (its least vertex)."""
    comp = np.arange(n)
    live = np.flatnonzero(u != v)
    a, b = u[live], v[live]
    kept: list[np.ndarray] = []
    none = len(u)
    while len(live):
        first = np.full(n, none)
        first[a[::-1]] = live[::-1]
        other = np.full(n, none)
        other[b[::-1]] = live[::-1]
        first = np.minimum(first, other)
        tops = np.flatnonzero(first < none)
        picked = first[tops]
        ends = comp[u[picked]], comp[v[picked]]
        far = np.where(ends[0] == tops, ends[1], ends[0])
        parent = np.arange(n)
        parent[tops] = far
        # two components that picked the same edge point at each other: the lesser one stays
        mutual = tops[(parent[far] == tops) & (tops < far)]
        parent[mutual] = mutual
        comp = _roots(parent)[comp]
        kept.append(np.unique(picked))
        a, b = comp[u[live]], comp[v[live]]
        keep = a != b
        live, a, b = live[keep], a[keep], b[keep]
    least = np.full(n, n)
    np.minimum.at(least, comp, np.arange(n))
    return np.sort(np.concatenate(kept)) if kept else np.empty(0, dtype=np.int64), least[comp]


def forest_of(u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Places of a spanning forest's edges, for any vertex numbers."""
    ids, a, b = compact(u, v)
    return forest(len(ids), a, b)[0]


def labels_of(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vertices and their components' least vertices."""
    ids, a, b = compact(u, v)
    return ids, ids[forest(len(ids), a, b)[1]]
