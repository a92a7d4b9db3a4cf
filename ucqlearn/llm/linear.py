"""Logistic regression on the driver over bounded samples: limited-memory quasi-Newton on dense or sparse rows."""

from __future__ import annotations

import numpy as np


class SparseRows:
    """Rows of feature numbers with one value a feature (all rows share ``scale``): ``ids`` of all rows in a line, and
    ``starts``, one more than rows. Products go block by block, so that temporary arrays stay small."""

    BLOCK = 1 << 18

    def __init__(self, ids: np.ndarray, starts: np.ndarray, scale: np.ndarray):
        self.ids, self.starts, self.n, self.scale = ids.astype(np.int32, copy=False), starts, len(starts) - 1, scale

    @classmethod
    def of(cls, rows: list[np.ndarray], scale: np.ndarray) -> "SparseRows":
        return cls(np.concatenate([*rows, np.zeros(0, dtype=np.int32)]), np.cumsum([0, *map(len, rows)]), scale)

    def _blocks(self):
        low = 0
        while low < self.n:
            high = max(low + 1, int(np.searchsorted(self.starts, self.starts[low] + self.BLOCK, side="right")) - 1)
            a, b = self.starts[low], self.starts[high]
            yield low, high, self.ids[a:b], np.repeat(np.arange(high - low), np.diff(self.starts[low : high + 1]))
            low = high

    def dot(self, w: np.ndarray) -> np.ndarray:
        out, scaled = np.zeros(self.n), w * self.scale
        for low, high, ids, row in self._blocks():
            out[low:high] = np.bincount(row, weights=scaled[ids], minlength=high - low)
        return out

    def back(self, g: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.scale))
        for low, high, ids, row in self._blocks():
            out += np.bincount(ids, weights=g[low:high][row], minlength=len(self.scale))
        return out * self.scale


class DenseRows:
    def __init__(self, x: np.ndarray):
        self.x, self.n = x, len(x)

    def dot(self, w):
        return self.x @ w

    def back(self, g):
        return g @ self.x


def sigmoid(m):
    return 0.5 * (1.0 + np.tanh(0.5 * m))


def fit_logistic(rows, y: np.ndarray, width: int, l2: float, weights: np.ndarray | None = None, rounds: int = 100, memory: int = 8) -> tuple[np.ndarray, float]:
    """(w, intercept) that minimise the mean log loss plus l2/2 |w|^2. With no rows, or one class only, w is 0."""
    weights = np.ones(len(y)) if weights is None else weights
    share = float((weights @ y) / weights.sum()) if len(y) else 0.5
    if not len(y) or share in (0.0, 1.0):
        return np.zeros(width), float(np.log((share + 1e-3) / (1 - share + 1e-3)))
    total = weights.sum()

    def value(p):
        m = rows.dot(p[:-1]) + p[-1]
        loss = (weights * (np.logaddexp(0.0, m) - y * m)).sum() / total + 0.5 * l2 * p[:-1] @ p[:-1]
        g = weights * (sigmoid(m) - y) / total
        return loss, np.concatenate([rows.back(g) + l2 * p[:-1], [g.sum()]])

    p = np.zeros(width + 1)
    p[-1] = np.log(share / (1 - share))
    f, g = value(p)
    past: list[tuple[np.ndarray, np.ndarray, float]] = []
    for _ in range(rounds):
        q, alphas = g.copy(), []
        for s, d, r in reversed(past):
            a = r * (s @ q)
            alphas.append(a)
            q -= a * d
        if past:
            s, d, _ = past[-1]
            q *= (s @ d) / (d @ d)
        for (s, d, r), a in zip(past, reversed(alphas)):
            q += (a - r * (d @ q)) * s
        step, slope = 1.0, -(g @ q)
        if slope >= 0:
            q, slope, past = g, -(g @ g), []
        while True:
            new = p - step * q
            f_new, g_new = value(new)
            if f_new <= f + 1e-4 * step * slope or step < 1e-10:
                break
            step *= 0.5
        s, d = new - p, g_new - g
        done = f - f_new <= 1e-9 * max(1.0, abs(f))
        p, f, g = new, f_new, g_new
        if s @ d > 1e-12:
            past = [*past, (s, d, 1.0 / (s @ d))][-memory:]
        if done or np.abs(g).max() < 1e-7:
            break
    return p[:-1], float(p[-1])
