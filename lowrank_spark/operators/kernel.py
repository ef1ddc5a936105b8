"""Numeric kernels of the stochastic solvers, on numpy only.

Entries of a block are cut into waves: in a wave no row and no column comes twice, so a wave is one vectorised step
that equals its entries' steps one after the other. The order of the entries fixes the waves, so a run is a pure
function of data, order and seed.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from lowrank_spark.config import TrainConfig


def rate(alpha: float, beta: float, t: float) -> float:
    return alpha / (1 + beta * t**1.5)


def wave_of(rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
    """The wave of every entry: one after the last wave of its row and of its column. rows and cols are places from 0 on."""
    last_r, last_c = ([-1] * (int(x.max()) + 1 if len(x) else 0) for x in (rows, cols))
    at = []
    for i, j in zip(rows.tolist(), cols.tolist(), strict=True):
        a, b = last_r[i], last_c[j]
        w = (a if a > b else b) + 1
        last_r[i] = last_c[j] = w
        at.append(w)
    return np.array(at, np.int64)


def waves(rows: np.ndarray, cols: np.ndarray) -> list[np.ndarray]:
    """Index sets, a wave each."""
    at = wave_of(rows, cols)
    order = np.argsort(at, kind="stable")
    cuts = np.flatnonzero(np.diff(at[order])) + 1
    return np.split(order, cuts) if len(order) else []


@dataclass
class Block:
    """Entries of a block with local indices, and its parameters (changed in place)."""

    rows: np.ndarray
    cols: np.ndarray
    r: np.ndarray
    b: np.ndarray
    u: np.ndarray
    bh: np.ndarray
    v: np.ndarray
    w: np.ndarray  # columns x K
    c: np.ndarray
    res: np.ndarray | None = None  # entries x K: residual at an explicit neighbour, else 0
    is_ex: np.ndarray | None = None  # entries x K
    is_im: np.ndarray | None = None


def predict_entries(x: Block, s, mu: float, cfg: TrainConfig, scales=None) -> np.ndarray:
    i, j = x.rows[s], x.cols[s]
    out = np.zeros(len(i))
    if "base" in cfg.parts:
        out += mu + x.b[i] + x.bh[j]
    if x.is_ex is not None and cfg.parts & {"explicit", "implicit"}:
        sx, si = scales if scales is not None else neighbour_scales(x)
        if "explicit" in cfg.parts:
            out += sx[s] * (x.res[s] * x.w[j]).sum(1)
        if "implicit" in cfg.parts:
            out += si[s] * (x.is_im[s] * x.c[j]).sum(1)
    if "factor" in cfg.parts:
        out += np.einsum("ef,ef->e", x.u[i], x.v[j])
    return out


def neighbour_scales(x: Block) -> tuple[np.ndarray, np.ndarray]:
    inv = lambda n: np.where(n > 0, 1 / np.sqrt(np.maximum(n, 1)), 0.0)
    return inv(x.is_ex.sum(1)), inv(x.is_im.sum(1))


def errors(r: np.ndarray, score: np.ndarray, loss: str) -> np.ndarray:
    return r - score if loss == "squared" else r - 1 / (1 + np.exp(-np.clip(score, -35, 35)))


def sgd(x: Block, mu: float, cfg: TrainConfig, t: int, freeze_rows: bool = False, freeze_cols: bool = False, order: list[np.ndarray] | None = None) -> None:
    """One pass over the block, in its waves (`order`, if they are known). Every update of an entry uses the values from before it."""
    a, lam = cfg.alpha, cfg.lam
    g = {k: rate(getattr(a, k), cfg.beta, t) for k in ("b", "bh", "u", "v", "w", "c")}
    near = x.is_ex is not None and bool(cfg.parts & {"explicit", "implicit"})
    scales = neighbour_scales(x) if near else None
    for s in waves(x.rows, x.cols) if order is None else order:
        i, j = x.rows[s], x.cols[s]
        e = errors(x.r[s], predict_entries(x, s, mu, cfg, scales), cfg.loss)
        ui, vj = x.u[i], x.v[j]
        if "base" in cfg.parts and cfg.use_bias:
            if not freeze_rows:
                x.b[i] += g["b"] * (e - lam.b * x.b[i])
            if not freeze_cols:
                x.bh[j] += g["bh"] * (e - lam.bh * x.bh[j])
        if near and not freeze_cols:
            sx, si = scales
            if "explicit" in cfg.parts:
                x.w[j] += g["w"] * x.is_ex[s] * ((sx[s] * e)[:, None] * x.res[s] - lam.w * x.w[j])
            if "implicit" in cfg.parts:
                x.c[j] += g["c"] * x.is_im[s] * ((si[s] * e)[:, None] - lam.c * x.c[j])
        if "factor" in cfg.parts:
            if not freeze_rows:
                x.u[i] = ui + g["u"] * (e[:, None] * vj - lam.u * ui)
            if not freeze_cols:
                x.v[j] = vj + g["v"] * (e[:, None] * ui - lam.v * vj)


def ridge_rows(owner: np.ndarray, r: np.ndarray, other: np.ndarray, lam: float, weighted: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(owners, solutions) of every owner's normal equations; entries may come in any order."""
    ids, at = np.unique(owner, return_inverse=True)
    order = np.argsort(at, kind="stable")
    at, r, other = at[order], r[order], other[order]
    starts = np.searchsorted(at, np.arange(len(ids)))
    ends = np.append(starts[1:], len(at))
    out = np.empty((len(ids), other.shape[1]))
    eye = np.eye(other.shape[1])
    for k, (lo, hi) in enumerate(zip(starts, ends, strict=True)):
        o = other[lo:hi]
        out[k] = np.linalg.solve(o.T @ o + lam * (hi - lo if weighted else 1) * eye, o.T @ r[lo:hi])
    return ids, out
