"""Gaussian-process surrogate: Matern-5/2 kernel, length scales by marginal likelihood."""

from __future__ import annotations

import numpy as np

from ...functions.blas import single_thread
from .base import register
from .surrogate import Surrogate

#: Observations that a fit takes at most (the newest), scales tried per dimension, jitter.
MOST, SCALES, JITTER = 1000, (0.1, 0.2, 0.4, 0.8, 1.6), 1e-4


def _kernel(a: np.ndarray, b: np.ndarray, scales: np.ndarray) -> np.ndarray:
    gap = (a[:, None, :] - b[None, :, :]) / scales
    r = np.sqrt(5.0 * np.maximum(0.0, (gap * gap).sum(axis=2)))
    return (1.0 + r + r * r / 3.0) * np.exp(-r)


def _fit(x: np.ndarray, z: np.ndarray, scales: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    k = _kernel(x, x, scales) + JITTER * np.eye(len(z))
    low = np.linalg.cholesky(k)
    alpha = np.linalg.solve(low.T, np.linalg.solve(low, z))
    return float(-0.5 * z @ alpha - np.log(np.diag(low)).sum()), low, alpha


class GaussianProcess(Surrogate):
    def model(self, x, y, candidates, rng):
        single_thread()
        x, y = x[-MOST:], y[-MOST:]
        centre, spread = y.mean(), y.std() or 1.0
        z = (y - centre) / spread
        scales = np.full(x.shape[1], 0.4)
        best = _fit(x, z, scales)
        for j in range(x.shape[1]):  # one pass of coordinate choice
            for s in SCALES:
                tried = scales.copy()
                tried[j] = s
                got = _fit(x, z, tried)
                if got[0] > best[0]:
                    best, scales = got, tried
        _, low, alpha = best
        cross = _kernel(candidates, x, scales)
        half = np.linalg.solve(low, cross.T)
        variance = np.maximum(1e-12, 1.0 + JITTER - (half * half).sum(axis=0))
        return centre + spread * (cross @ alpha), spread * np.sqrt(variance)


register("gaussian_process", GaussianProcess)
