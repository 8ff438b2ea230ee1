"""Random feature maps: cosine features of Gaussian or Cauchy projections.

The projection of a map follows from its seed, so it is drawn again in every task and never sent.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


#: Columns that one generator draws.
GROUP = 256


@dataclass(frozen=True)
class Projection:
    """``size`` features of inputs with ``d`` columns.  ``noise`` multiplies the draws; ``skew``
    shifts their location (a reading of a parameter the reference does not define)."""

    d: int
    size: int
    seed: int = 0
    noise: float = 1.0
    dist: str = "gaussian"
    skew: float = 0.0

    def matrix(self, first: int = 0, count: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Columns ``first`` .. of the projection and their phases."""
        count = self.size - first if count is None else count
        groups = []
        # columns are drawn by groups that depend on their number only, so blocks of columns agree
        for g in range(first // GROUP, -(-(first + count) // GROUP)):
            rng = np.random.Generator(np.random.PCG64([self.seed, g]))
            draw = rng.standard_cauchy((GROUP, self.d)) if self.dist == "cauchy" else rng.standard_normal((GROUP, self.d))
            groups.append((draw, rng.random(GROUP)))
        own = slice(first % GROUP, first % GROUP + count)
        omega = self.noise * (np.concatenate([d for d, _ in groups])[own] + self.skew) if groups else np.empty((0, self.d))
        return np.ascontiguousarray(omega.T), (np.concatenate([p for _, p in groups])[own] if groups else np.empty(0)) * 2 * math.pi

    def apply(self, x: np.ndarray, omega: np.ndarray, phase: np.ndarray) -> np.ndarray:
        z = x @ omega
        z += phase
        np.cos(z, out=z)
        z *= math.sqrt(2.0 / self.size)
        return z

    def transform(self, x: np.ndarray) -> np.ndarray:
        return self.apply(x, *self.matrix())


class Components:
    """The leading principal components of a training split as a feature map: a first stage whose
    size is a parameter of the search like any other."""

    def __init__(self, mean: np.ndarray, vectors: np.ndarray, size: int):
        self.mean, self.vectors, self.d, self.size = mean, vectors[:, :size], len(mean), size

    def matrix(self) -> tuple[np.ndarray, np.ndarray]:
        return self.vectors, self.mean

    def apply(self, x: np.ndarray, vectors: np.ndarray, mean: np.ndarray) -> np.ndarray:
        return (x - mean) @ vectors

    def transform(self, x: np.ndarray) -> np.ndarray:
        return self.apply(x, *self.matrix())
