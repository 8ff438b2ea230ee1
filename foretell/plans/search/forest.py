"""Random-forest surrogate with expected improvement; every second proposal is random."""

from __future__ import annotations

import numpy as np

from .base import register
from .surrogate import Surrogate

#: Published settings: trees, smallest leaf.
TREES, LEAF = 10, 3


def _grow(x: np.ndarray, y: np.ndarray, rng: np.random.Generator, depth: int = 0):
    if len(y) < 2 * LEAF or depth > 12 or np.ptp(y) < 1e-12:
        return float(y.mean())
    best = None
    for j in rng.permutation(x.shape[1])[: max(1, (x.shape[1] * 5 + 5) // 6)]:
        order = np.argsort(x[:, j], kind="stable")
        v, t = x[order, j], y[order]
        left, left2 = np.cumsum(t), np.cumsum(t * t)
        n = np.arange(1, len(t) + 1)
        cost = (left2 - left**2 / n)[:-1] + (left2[-1] - left2[:-1]) - (left[-1] - left[:-1]) ** 2 / (len(t) - n[:-1])
        ok = (v[1:] > v[:-1]) & (n[:-1] >= LEAF) & (len(t) - n[:-1] >= LEAF)
        if ok.any():
            i = int(np.argmin(np.where(ok, cost, np.inf)))
            if best is None or cost[i] < best[0]:
                best = (cost[i], j, v[i] + rng.random() * (v[i + 1] - v[i]))
    if best is None:
        return float(y.mean())
    side = x[:, best[1]] <= best[2]
    return best[1], best[2], _grow(x[side], y[side], rng, depth + 1), _grow(x[~side], y[~side], rng, depth + 1)


def _read(tree, x: np.ndarray) -> np.ndarray:
    if isinstance(tree, float):
        return np.full(len(x), tree)
    j, cut, low, high = tree
    side = x[:, j] <= cut
    out = np.empty(len(x))
    out[side], out[~side] = _read(low, x[side]), _read(high, x[~side])
    return out


class Forest(Surrogate):
    def explores(self) -> bool:
        return self.at % 2 == 1

    def model(self, x, y, candidates, rng):
        rows = []
        for _ in range(TREES):
            pick = rng.integers(len(y), size=len(y))
            rows.append(_read(_grow(x[pick], y[pick], rng), candidates))
        guesses = np.stack(rows)
        return guesses.mean(axis=0), guesses.std(axis=0)


register("forest", Forest)
