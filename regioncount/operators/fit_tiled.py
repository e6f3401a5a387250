"""L1 fit of lattices too large for one task: the saddle-point iteration on tiles.

A tile row holds its part of the noisy, current and extrapolated values and the multipliers of the constraints whose
lower node it owns. In a round every tile sends border strips as wide as the information of `inner` steps travels to
its eight neighbours, is put together with theirs, and makes `inner` steps; what it keeps of the result equals the
iteration on the whole lattice. Rounds are written to the shared folder. The driver sees two numbers a round.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.operators.schemas import GridSpec
from regioncount.sources.shared import cut

_FIELDS = ("y", "x", "bar", "zw", "ze", "zn", "zs")
_SHIFT = {"zw": (0, -1), "ze": (0, 1), "zn": (-1, 0), "zs": (1, 0)}
_SCHEMA = "tu int, tv int, u0 int, v0 int, rows int, cols int, data binary"


def _shift(a: np.ndarray, du: int, dv: int, fill: float) -> np.ndarray:
    """out[u, v] = a[u + du, v + dv], `fill` outside."""
    out = np.full_like(a, fill)
    h, w = a.shape
    out[max(0, -du) : h - max(0, du), max(0, -dv) : w - max(0, dv)] = a[max(0, du) : h - max(0, -du), max(0, dv) : w - max(0, -dv)]
    return out


def _masks(shape, u0: int, v0: int) -> dict[str, np.ndarray]:
    u, v = np.meshgrid(np.arange(shape[0]) + u0, np.arange(shape[1]) + v0, indexing="ij")
    return {"zw": v % 2 == 1, "ze": v % 2 == 1, "zn": u % 2 == 1, "zs": u % 2 == 1}


def _back(f: dict[str, np.ndarray]) -> np.ndarray:
    out = np.zeros_like(f["x"])
    for z, (du, dv) in _SHIFT.items():
        out += f[z] - _shift(f[z], -du, -dv, 0.0)
    return out


def _step(f: dict[str, np.ndarray], masks, tau: float, sigma: float) -> None:
    for z, (du, dv) in _SHIFT.items():
        f[z] = np.where(masks[z], np.maximum(f[z] + sigma * (f["bar"] - _shift(f["bar"], du, dv, np.inf)), 0), 0)
    t = f["x"] - tau * _back(f)
    new = np.maximum(f["y"] + np.sign(t - f["y"]) * np.maximum(np.abs(t - f["y"]) - tau, 0), 0)
    f["bar"], f["x"] = 2 * new - f["x"], new


def _repair(x: np.ndarray, u0: int, v0: int) -> np.ndarray:
    x, m = np.maximum(x, 0), _masks(x.shape, u0, v0)
    vertex = m["zw"] & m["zn"]
    for stage in (~vertex, vertex):
        low = x.copy()
        for z, (du, dv) in _SHIFT.items():
            low = np.where(m[z] & stage, np.minimum(low, _shift(x, du, dv, np.inf)), low)
        x = low
    return x


def _pack(f: dict[str, np.ndarray]) -> bytes:
    return np.stack([f[k] for k in _FIELDS]).tobytes()


def _unpack(r) -> dict[str, np.ndarray]:
    return dict(zip(_FIELDS, np.frombuffer(r.data).reshape(len(_FIELDS), r.rows, r.cols).copy(), strict=True))


def tiles(noisy: DataFrame, tile: int) -> DataFrame:
    """Tile rows of a dense lattice."""

    def run(p: pd.DataFrame) -> pd.DataFrame:
        u0, v0 = int(p.u.min()), int(p.v.min())
        y = np.zeros((int(p.u.max()) - u0 + 1, int(p.v.max()) - v0 + 1))
        y[p.u - u0, p.v - v0] = p.h
        zero = np.zeros_like(y)
        f = {"y": y, "x": y.copy(), "bar": y.copy(), "zw": zero, "ze": zero, "zn": zero, "zs": zero}
        return pd.DataFrame({"tu": [int(p.tu.iloc[0])], "tv": [int(p.tv.iloc[0])], "u0": [u0], "v0": [v0], "rows": [y.shape[0]], "cols": [y.shape[1]], "data": [_pack(f)]})

    at = lambda c: F.floor(F.col(c) / tile).cast("int")
    return noisy.select("u", "v", F.col("h").cast("double").alias("h"), at("u").alias("tu"), at("v").alias("tv")).groupBy("tu", "tv").applyInPandas(run, _SCHEMA)


def _with_halos(state: DataFrame, halo: int, tile: int, then, schema: str) -> DataFrame:
    """Run `then(fields, u0, v0, slices of the own tile, tu, tv)` on every tile widened by its neighbours' strips."""

    def send(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in frames:
            out = []
            for r in p.itertuples():
                f = _unpack(r)
                for du in (-1, 0, 1):
                    for dv in (-1, 0, 1):
                        a = slice(0, halo) if du < 0 else slice(max(0, r.rows - halo), r.rows) if du > 0 else slice(0, r.rows)
                        b = slice(0, halo) if dv < 0 else slice(max(0, r.cols - halo), r.cols) if dv > 0 else slice(0, r.cols)
                        part = {k: x[a, b] for k, x in f.items()}
                        h, w = part["y"].shape
                        out.append((r.tu + du, r.tv + dv, r.u0 + a.start, r.v0 + b.start, h, w, _pack(part), du == 0 and dv == 0))
            yield pd.DataFrame(out, columns=["tu", "tv", "u0", "v0", "rows", "cols", "data", "own"])

    def receive(p: pd.DataFrame) -> pd.DataFrame:
        if not p.own.any():
            return pd.DataFrame({c.strip().split(" ")[0]: [] for c in schema.split(",")})
        u0, v0 = int(p.u0.min()), int(p.v0.min())
        shape = (int((p.u0 + p.rows).max()) - u0, int((p.v0 + p.cols).max()) - v0)
        f = {k: np.zeros(shape) for k in _FIELDS}
        own = None
        for r in p.itertuples():
            a, b = slice(r.u0 - u0, r.u0 - u0 + r.rows), slice(r.v0 - v0, r.v0 - v0 + r.cols)
            for k, x in _unpack(r).items():
                f[k][a, b] = x
            if r.own:
                own = (a, b)
        return then(f, u0, v0, own, int(p.tu.iloc[0]), int(p.tv.iloc[0]))

    return state.mapInPandas(send, _SCHEMA + ", own boolean").groupBy("tu", "tv").applyInPandas(receive, schema)


def l1(noisy: DataFrame, spec: GridSpec, tile: int = 512, rounds: int = 200, inner: int = 8, tolerance: float = 1e-3, tau: float = 5.0, check_every: int = 10) -> tuple[DataFrame, float, int]:
    """(fitted lattice, certified relative gap, rounds made)."""
    inner = max(1, min(inner, tile // 2 - 1))
    halo, sigma = 2 * inner, 0.99 / (8 * tau)
    if halo > tile:
        raise ValueError("a tile is at least twice as wide as the inner steps")

    def advance(f, u0, v0, own, tu, tv):
        masks = _masks(f["y"].shape, u0, v0)
        for _ in range(inner):
            _step(f, masks, tau, sigma)
        mine = {k: x[own] for k, x in f.items()}
        h, w = mine["y"].shape
        return pd.DataFrame({"tu": [tu], "tv": [tv], "u0": [u0 + own[0].start], "v0": [v0 + own[1].start], "rows": [h], "cols": [w], "data": [_pack(mine)]})

    def lowest(f, u0, v0, own, tu, tv):
        return pd.DataFrame({"low": [float(_back(f)[own].min())]})

    def terms(scale):
        def run(f, u0, v0, own, tu, tv):
            y = f["y"][own]
            fit = _repair(f["x"], u0, v0)[own]
            return pd.DataFrame({"objective": [float(np.abs(fit - y).sum())], "bound": [float((np.minimum(_back(f)[own] * scale, 1.0) * y).sum())]})

        return run

    state, gap, made = cut(tiles(noisy, tile)), float("inf"), 0
    for made in range(1, rounds + 1):
        state = _with_halos(state, halo, tile, advance, _SCHEMA)
        if made % check_every == 0 or made == rounds:
            state = cut(state)
            low = _with_halos(state, 2, tile, lowest, "low double").agg(F.min("low")).first()[0]
            row = _with_halos(state, 2, tile, terms(min(1.0, 1.0 / max(1e-12, -low))), "objective double, bound double").agg(F.sum("objective"), F.sum("bound")).first()
            gap = (row[0] - row[1]) / max(1.0, row[0])
            if gap <= tolerance:
                break

    def result(f, u0, v0, own, tu, tv):
        fit = _repair(f["x"], u0, v0)[own]
        u, v = np.meshgrid(np.arange(fit.shape[0]) + u0 + own[0].start, np.arange(fit.shape[1]) + v0 + own[1].start, indexing="ij")
        return pd.DataFrame({"u": u.ravel().astype("int32"), "v": v.ravel().astype("int32"), "h": fit.ravel()})

    fitted = _with_halos(state, 2, tile, result, "u int, v int, h double")
    return noisy.select("u", "v", "kind").join(fitted, ["u", "v"]), float(gap), made
