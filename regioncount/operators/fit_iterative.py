"""First-order fits on a lattice as numpy stencils: L1 by a saddle-point iteration, L2 by corrected projections.

Order constraints are array slices: a node of odd index minus its even neighbour, along either axis, is at most 0.
"""

from __future__ import annotations

import numpy as np

_ODD, _LEFT, _RIGHT = slice(1, None, 2), slice(0, -1, 2), slice(2, None, 2)


def _cuts(classes) -> list[tuple[tuple, tuple]]:
    """(lower, upper) slices of the order constraints."""
    out = []
    for side in (_LEFT, _RIGHT):
        for parity, cls in ((slice(0, None, 2), "C1"), (_ODD, "C2")):
            if cls in classes:
                out += [((parity, _ODD), (parity, side)), ((_ODD, parity), (side, parity))]
    return out


def _blocks(x: np.ndarray) -> np.ndarray:
    """Signed three-by-three sum round each vertex."""
    sign = np.where(np.add.outer(np.arange(x.shape[0]), np.arange(x.shape[1])) % 2 == 0, 1.0, -1.0) * x
    rows = sign[0:-2:2] + sign[1:-1:2] + sign[2::2]
    return rows[:, 0:-2:2] + rows[:, 1:-1:2] + rows[:, 2::2]


def _blocks_back(z: np.ndarray, shape) -> np.ndarray:
    out = np.zeros(shape)
    for a, rows in enumerate((slice(0, -2, 2), slice(1, -1, 2), slice(2, None, 2))):
        for b, columns in enumerate((slice(0, -2, 2), slice(1, -1, 2), slice(2, None, 2))):
            out[rows, columns] += z * (1.0 if (a + b) % 2 == 0 else -1.0)
    return out


def violations(x: np.ndarray, tolerance: float = 0.0) -> int:
    return sum(int((x[lo] - x[up] > tolerance).sum()) for lo, up in _cuts(("C1", "C2"))) + int((_blocks(x) < -tolerance).sum())


def repair(x: np.ndarray, classes=("C1", "C2", "C3")) -> np.ndarray:
    """A lattice that meets these classes: edges lowered to their faces, then vertices to their edges; then, where a
    block is still below 0, its vertex is raised, or, if vertices are bound by their edges, one of its faces.

    C1 and C2 together imply C3. Without C2 no class bounds a vertex from above, and without C1 none a face.
    """
    x = np.maximum(x, 0)
    for lo, up in sorted(_cuts(classes), key=lambda c: c[0] == (_ODD, _ODD)):
        x[lo] = np.minimum(x[lo], x[up])
    if "C3" in classes and not {"C1", "C2"} <= set(classes):
        raised = (slice(0, -2, 2),) * 2 if "C2" in classes else (_ODD, _ODD)
        while (short := -_blocks(x)).max(initial=0) > 0:
            # a little more than what is missing, so that rounding leaves nothing
            x[raised] += np.where(short > 0, short * (1 + 1e-12) + 1e-12, 0)
    return x


def _nearest(z: np.ndarray, y: np.ndarray, tau: float, prior: float | None, weight: float) -> np.ndarray:
    """Minimiser of |x - y| + weight |x - prior| + (x - z)^2 / (2 tau)."""
    if not weight:
        return y + np.sign(z - y) * np.maximum(np.abs(z - y) - tau, 0)
    p = np.full_like(y, prior)
    first, last = np.minimum(y, p), np.maximum(y, p)
    w1 = np.where(y <= p, 1.0, weight)
    total = 1.0 + weight
    options = np.stack([first, last, z + tau * total, z + tau * (total - 2 * w1), z - tau * total])
    return np.median(options, axis=0)


def l1(y: np.ndarray, steps: int = 2000, classes=("C1", "C2", "C3"), prior: float | None = None, weight: float = 0.0, tolerance: float = 1e-9, tau: float = 5.0) -> tuple[np.ndarray, float]:
    """(fit, lower bound on the objective of any feasible lattice; nan with a prior or other classes)."""
    cuts = _cuts(classes)
    use_blocks = "C3" in classes and not {"C1", "C2"} <= set(classes)
    full = {"C1", "C2"} <= set(classes)
    x = repair(y.copy(), classes)
    bar, z = x.copy(), [np.zeros(x[lo].shape) for lo, _ in cuts]
    zb = np.zeros((y.shape[0] // 2, y.shape[1] // 2))
    sigma = 0.99 / (tau * (8 + 9 * use_blocks))
    best, best_value, bound = None, np.inf, -np.inf
    for step in range(1, steps + 1):
        back = np.zeros_like(x)
        for k, (lo, up) in enumerate(cuts):
            z[k] = np.maximum(z[k] + sigma * (bar[lo] - bar[up]), 0)
            back[lo] += z[k]
            back[up] -= z[k]
        if use_blocks:
            zb = np.maximum(zb - sigma * _blocks(bar), 0)
            back -= _blocks_back(zb, x.shape)
        new = np.maximum(_nearest(x - tau * back, y, tau, prior, weight), 0)
        bar, x = 2 * new - x, new
        if step % 100 == 0 or step == steps:
            feasible = repair(x.copy(), classes)
            value = np.abs(feasible - y).sum() + (weight * np.abs(feasible - prior).sum() if weight else 0.0)
            if value < best_value:
                best, best_value = feasible, value
            if full and not weight:
                scale = min(1.0, 1.0 / max(1e-12, -back.min()))
                bound = max(bound, float((np.minimum(back * scale, 1.0) * y).sum()))
                if best_value - bound <= tolerance * max(1.0, best_value):
                    break
    return best, bound if full and not weight else float("nan")


def l2(y: np.ndarray, tolerance: float = 1e-7, sweeps: int = 5000) -> np.ndarray:
    """Nearest in squares: cyclic projections onto each family of disjoint pairs, with corrections, and onto x >= 0."""
    cuts = _cuts(("C1", "C2"))
    x = y.astype(float).copy()
    gone = [np.zeros(x[lo].shape) for lo, _ in cuts]
    low = np.zeros_like(x)
    for _ in range(sweeps):
        before = x.copy()
        for k, (lo, up) in enumerate(cuts):
            a, b = x[lo] + gone[k], x[up] - gone[k]
            gone[k] = np.maximum((a - b) / 2, 0)
            x[lo], x[up] = a - gone[k], b + gone[k]
        t = x + low
        x = np.maximum(t, 0)
        low = t - x
        if np.abs(x - before).max() < tolerance:
            break
    return repair(x)
