"""Exact L1 fit on a lattice by splitting values and matching.

The distinct noisy values are split in the middle. Every node of a set wants the half its own value is in; a node that
wants the upper half below one that wants the lower half is a conflict. Fewest nodes to change sides are a least
vertex cover of the conflicts, which a largest matching gives. Both halves are then fitted on their own. Ties between
covers go to the one reachable from the unmatched lower side.
"""

from __future__ import annotations

from collections import deque

import numpy as np


def above(side: int) -> list[list[int]]:
    """For each node, the nodes that bound it from above: faces of an edge; edges and faces of a vertex."""
    out = []
    for u in range(side):
        for v in range(side):
            ups = []
            for du in (-1, 0, 1):
                for dv in (-1, 0, 1):
                    a, b = u + du, v + dv
                    if (du or dv) and 0 <= a < side and 0 <= b < side and a % 2 <= u % 2 and b % 2 <= v % 2 and (du == 0 or u % 2) and (dv == 0 or v % 2):
                        ups.append(a * side + b)
            out.append(ups)
    return out


_ABOVE: dict[int, list[list[int]]] = {}


def l1(y: np.ndarray) -> np.ndarray:
    """Nearest monotone, non-negative lattice in the sum of absolute changes. Negative values are clipped at 0 first:
    with the order constraints, a best fit of the clipped values is one of the values themselves."""
    side = y.shape[0]
    ups = _ABOVE.setdefault(side, above(side))
    flat = np.maximum(y, 0).ravel()
    values = np.unique(flat)
    rank = np.searchsorted(values, flat).tolist()
    out = np.empty(len(flat))
    where = [0] * len(flat)
    stack, label = [(list(range(len(flat))), 0, len(values) - 1)], 0
    while stack:
        nodes, lo, hi = stack.pop()
        if lo == hi:
            out[nodes] = values[lo]
            continue
        mid, label = (lo + hi) // 2, label + 1
        for i in nodes:
            where[i] = label
        high = {i for i in nodes if rank[i] > mid}
        conflicts = {i: c for i in high if (c := [j for j in ups[i] if where[j] == label and j not in high])}
        for i in _cover(conflicts):
            high.symmetric_difference_update((i,))
        upper = [i for i in nodes if i in high]
        lower = [i for i in nodes if i not in high]
        if upper:
            stack.append((upper, mid + 1, hi))
        if lower:
            stack.append((lower, lo, mid))
    return out.reshape(y.shape)


def _cover(links: dict[int, list[int]]) -> set[int]:
    """Least vertex cover of a bipartite graph, by layered augmenting paths."""
    mate_a: dict[int, int] = {}
    mate_b: dict[int, int] = {}
    for a, bs in links.items():
        for b in bs:
            if b not in mate_b:
                mate_a[a], mate_b[b] = b, a
                break
    while True:
        depth = {a: 0 for a in links if a not in mate_a}
        queue, found = deque(depth), False
        while queue:
            a = queue.popleft()
            for b in links[a]:
                c = mate_b.get(b)
                if c is None:
                    found = True
                elif c not in depth:
                    depth[c] = depth[a] + 1
                    queue.append(c)
        if not found:
            break
        tried = {a: 0 for a in depth}
        for root in [a for a in links if a not in mate_a]:
            path = [root]
            while path:
                a = path[-1]
                if tried[a] >= len(links[a]):
                    path.pop()
                    if path:
                        tried[path[-1]] += 1
                    continue
                b = links[a][tried[a]]
                c = mate_b.get(b)
                if c is None:
                    for p in reversed(path):
                        q = links[p][tried[p]]
                        mate_a[p], mate_b[q] = q, p
                    for p in path:
                        tried[p] = len(links[p])
                    path = []
                elif depth.get(c, -1) == depth[a] + 1 and tried[c] < len(links[c]):
                    path.append(c)
                else:
                    tried[a] += 1
    reached_a, reached_b = {a for a in links if a not in mate_a}, set()
    queue = deque(reached_a)
    while queue:
        for b in links[queue.popleft()]:
            if b not in reached_b:
                reached_b.add(b)
                c = mate_b[b]
                if c not in reached_a:
                    reached_a.add(c)
                    queue.append(c)
    return (set(links) - reached_a) | reached_b
