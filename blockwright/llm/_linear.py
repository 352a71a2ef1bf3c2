"""Small numpy fitters shared by the classifiers; every one is deterministic."""

from __future__ import annotations

import numpy as np


def platt(margin: np.ndarray, y: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """(a, b) of sigmoid(a*margin + b), by damped Newton with the usual smoothed targets."""
    pos, neg = float(y.sum()), float(len(y) - y.sum())
    t = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    scale = float(margin.std()) or 1.0
    m = margin / scale
    a, b = 1.0, 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a * m + b, -30, 30)))
        g = np.array([((p - t) * m).sum() + 1e-3 * a, (p - t).sum()])
        w = p * (1 - p) + 1e-9
        h = np.array([[(w * m * m).sum() + 1e-3, (w * m).sum()], [(w * m).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        step *= min(1.0, 2 / (np.abs(step).max() + 1e-12))
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return a / scale, b


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def logistic(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, dims: int, l2: float = 1e-6, rounds: int = 120, rate: float = 0.3) -> tuple[np.ndarray, float]:
    """Weights and intercept of class-balanced logistic regression over sparse rows (indices, values), by full-batch Adam. `rows` is used up."""
    n_of = np.array([len(r[0]) for r in rows])
    ends = np.concatenate([[0], np.cumsum(n_of)])
    idx, val = np.empty(ends[-1], np.int32), np.empty(ends[-1], np.float32)
    seen = np.zeros(dims, bool)
    for i in range(len(rows)):
        idx[ends[i] : ends[i + 1]], val[ends[i] : ends[i + 1]] = rows[i]
        seen[rows[i][0]] = True
        rows[i] = None  # the arrays now hold it
    # only features that occur have a weight
    used = np.flatnonzero(seen)
    number = np.zeros(dims, np.int32)
    number[used] = np.arange(len(used))
    # blocks of rows keep what a step needs beside the data small
    cuts = np.unique(np.searchsorted(ends, np.arange(0, ends[-1] + (1 << 19), 1 << 19)).clip(0, len(rows)))
    blocks = [(i, j, ends[i], ends[j]) for i, j in zip(cuts[:-1], cuts[1:])]
    for _, _, lo, hi in blocks:
        idx[lo:hi] = number[idx[lo:hi]]
    share = np.where(y > 0, 0.5 / max(y.sum(), 1), 0.5 / max((1 - y).sum(), 1))
    w, b = np.zeros(len(used)), 0.0
    m, v, mb, vb = np.zeros(len(used)), np.zeros(len(used)), 0.0, 0.0
    for k in range(1, rounds + 1):
        g, gb = l2 * w, 0.0
        w32 = w.astype(np.float32)
        for i, j, lo, hi in blocks:
            x, c = val[lo:hi], idx[lo:hi]
            total = np.concatenate([[0.0], np.cumsum(x * w32[c], dtype=np.float64)])
            d = (sigmoid(total[ends[i + 1 : j + 1] - lo] - total[ends[i:j] - lo] + b) - y[i:j]) * share[i:j]
            g += np.bincount(c, x * np.repeat(d, n_of[i:j]), len(used))
            gb += d.sum()
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        c1, c2 = 1 - 0.9**k, 1 - 0.99**k
        w -= rate * (m / c1) / (np.sqrt(v / c2) + 1e-9)
        b -= rate * (mb / c1) / (np.sqrt(vb / c2) + 1e-9)
    out = np.zeros(dims, np.float32)
    out[used] = w
    return out, float(b)
