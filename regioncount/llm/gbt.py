"""Gradient-boosted trees for two classes, in numpy: histogram splits on binned features, logistic loss."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Trees:
    """Complete binary trees of one depth: for node k, children 2k+1 and 2k+2; a leaf value for each path."""

    feature: np.ndarray  # (trees, inner nodes)
    cut: np.ndarray  # (trees, inner nodes): right if value > cut
    leaf: np.ndarray  # (trees, leaves)
    bias: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.bias)
        inner, rows = self.feature.shape[1], np.arange(len(x))
        for f, c, v in zip(self.feature, self.cut, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            while inner and node[0:1].size and node[0] < inner:
                node = 2 * node + 1 + (x[rows, f[node]] > c[node])
            out += v[node - inner]
        return out

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x), -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 40, depth: int = 4, rate: float = 0.3, bins: int = 32, l2: float = 1.0, least: float = 1.0) -> Trees:
    """Boost `trees` trees of `depth` levels by second-order gains; `least` is the least hessian of a leaf."""
    n, k = x.shape
    inner, leaves = 2**depth - 1, 2**depth
    edges = []
    for j in range(k):
        v = np.unique(x[:, j])
        mid = (v[1:] + v[:-1]) / 2
        edges.append(mid if len(mid) < bins else np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])))
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1) if k else np.zeros((n, 0), int)
    share = np.clip(y.mean() if n else 0.5, 1e-3, 1 - 1e-3)
    bias = float(np.log(share / (1 - share)))
    score = np.full(n, bias)
    out = Trees(np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf), np.zeros((trees, leaves)), bias)
    for t in range(trees):
        p = 1 / (1 + np.exp(-score))
        g, h = y - p, p * (1 - p)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            base, width = 2**level - 1, 2**level
            at = node - base
            gain, choice = np.full(width, 1e-6), [None] * width
            for j in range(k):
                size = len(edges[j]) + 1
                if size < 2:
                    continue
                key = at * size + binned[:, j]
                gs = np.bincount(key, g, width * size).reshape(width, size)
                hs = np.bincount(key, h, width * size).reshape(width, size)
                gl, hl = np.cumsum(gs, axis=1)[:, :-1], np.cumsum(hs, axis=1)[:, :-1]
                ga, ha = gs.sum(axis=1, keepdims=True), hs.sum(axis=1, keepdims=True)
                better = gl**2 / (hl + l2) + (ga - gl) ** 2 / (ha - hl + l2) - ga**2 / (ha + l2)
                better[(hl < least) | (ha - hl < least)] = -1
                best = better.argmax(axis=1)
                value = better[np.arange(width), best]
                for w in np.flatnonzero(value > gain):
                    gain[w], choice[w] = value[w], (j, edges[j][best[w]])
            for w, found in enumerate(choice):
                if found:
                    out.feature[t, base + w], out.cut[t, base + w] = found
            node = 2 * node + 1 + (x[np.arange(n), out.feature[t, node]] > out.cut[t, node])
        at = node - inner
        value = rate * np.bincount(at, g, leaves) / (np.bincount(at, h, leaves) + l2)
        out.leaf[t] = value
        score = score + value[at]
    return out
