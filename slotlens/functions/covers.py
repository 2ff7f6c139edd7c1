"""Clique covers of small similarity graphs: greedy and exact, plain numpy."""

from __future__ import annotations

import numpy as np

SLACK = 1e-12


def distances(v: np.ndarray) -> np.ndarray:
    d = v[:, None, :] - v[None, :, :]
    return np.sqrt((d * d).sum(axis=2))


def threshold_graph(d: np.ndarray, s0: float) -> np.ndarray:
    """Edge where the similarity 1 / distance reaches s0; coinciding vectors are always joined."""
    near = d * s0 <= 1 + SLACK if np.isfinite(s0) else d == 0
    near = near.copy()
    np.fill_diagonal(near, False)
    return near


def greedy(adjacent: np.ndarray, degree: str = "residual", order: str = "id", d: np.ndarray | None = None) -> np.ndarray:
    """Group of each vertex: seed of highest degree (least id among equals), then each neighbour that fits.

    degree: counted among uncovered vertices or once over the whole graph. order of neighbours: id, degree, nearest.
    """
    n = len(adjacent)
    label, free, group = np.full(n, -1), np.ones(n, bool), 0
    deg = adjacent.sum(axis=1)
    while free.any():
        v = int(np.where(free, deg, -1).argmax())
        around = np.flatnonzero(adjacent[v] & free)
        if order == "degree":
            around = around[np.argsort(-deg[around], kind="stable")]
        elif order == "nearest":
            around = around[np.argsort(d[v, around], kind="stable")]
        fits = adjacent[v].copy()
        label[v], free[v] = group, False
        for w in around:
            if fits[w]:
                label[w], free[w] = group, False
                fits &= adjacent[w]
        if degree == "residual":
            deg = deg - adjacent[:, np.flatnonzero(label == group)].sum(axis=1)
        group += 1
    return label


def exact(adjacent: np.ndarray) -> np.ndarray:
    """A cover with the least number of cliques, by branch and bound; for graphs of some tens of vertices.

    The vertex that fits the fewest groups so far goes next. Vertices no two of which are joined need a group each:
    a greedy set of them is the bound at which the search ends.
    """
    n = len(adjacent)
    best = greedy(adjacent)
    near = [sum(1 << int(w) for w in np.flatnonzero(adjacent[v])) for v in range(n)]
    apart, bound = (1 << n) - 1, 0
    for v in sorted(range(n), key=lambda v: near[v].bit_count()):
        if apart >> v & 1:
            bound += 1
            apart &= ~(near[v] | 1 << v)
    groups: list[int] = []

    def place(left: int) -> None:
        nonlocal best
        most = int(best.max()) + 1
        if len(groups) >= most or most == bound:
            return
        if not left:
            best = np.array([next(g for g, members in enumerate(groups) if members >> v & 1) for v in range(n)])
            return
        fits = {v: [g for g, members in enumerate(groups) if not members & ~near[v]] for v in range(n) if left >> v & 1}
        v = min(fits, key=lambda v: (len(fits[v]), near[v].bit_count()))
        for g in fits[v]:
            groups[g] |= 1 << v
            place(left & ~(1 << v))
            groups[g] &= ~(1 << v)
        groups.append(1 << v)
        place(left & ~(1 << v))
        groups.pop()

    if n:
        place((1 << n) - 1)
    return best


def cover_curve(v: np.ndarray, grid: np.ndarray | None = None, most_groups: int | None = None, **how) -> list[tuple[float, np.ndarray]]:
    """(s0, labels) from small to large thresholds, one per distinct number of groups, the first that is met.

    Without a grid the thresholds are all distinct distances, at every size, and are bisected: wherever the number of
    groups differs between two of them, the ones between are tried too, down to neighbours. The number may rise and
    fall again in a stretch with the same number at both ends: stretches next to a number that is still missing are
    tried whole. The covers tried are about as many as the groups, times the logarithm of the distances; numbers
    above ``most_groups`` are not sought.
    """
    d = distances(v)
    if grid is None:
        pairs = np.unique(d[np.triu_indices(len(v), 1)])
        pairs = pairs[pairs > 0]
        # Thresholds lie between pair values, so that no pair sits exactly on one.
        grid = 1 / np.concatenate([[pairs[-1] * 1.01], ((pairs[1:] + pairs[:-1]) / 2)[::-1], [pairs[0] / 2]]) if len(pairs) else np.array([1.0])
        tried: dict[int, np.ndarray] = {}

        def count(k: int) -> int:
            if k not in tried:
                tried[k] = greedy(threshold_graph(d, grid[k]), d=d, **how)
            return int(tried[k].max(initial=-1)) + 1

        limit = most_groups or len(v)
        spans, even = [(0, len(grid) - 1)], []
        while spans:
            i, j = spans.pop()
            a, b = count(i), count(j)
            if j - i > 1 and a == b:
                even.append((i, j, a))
            elif j - i > 1 and min(a, b) <= limit:
                spans += [(i, (i + j) // 2), ((i + j) // 2, j)]
        missing = set(range(1, limit + 1)) - {count(k) for k in list(tried)}
        for i, j, a in even:
            if a - 1 in missing or a + 1 in missing:
                for k in range(i + 1, j):
                    count(k)
        labels = [(float(grid[k]), tried[k]) for k in sorted(tried)]
    else:
        labels = [(float(s0), greedy(threshold_graph(d, s0), d=d, **how)) for s0 in grid]
    out, met = [], set()
    for s0, label in labels:
        n = int(label.max(initial=-1)) + 1
        if n not in met and (most_groups is None or n <= most_groups):
            met.add(n)
            out.append((s0, label))
    return out
