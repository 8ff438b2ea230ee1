"""Common part of the two surrogate methods: expected improvement over encoded configurations."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np

from ..space import Config
from .base import Observation, Proposer

#: Random candidates, best points perturbed, perturbations of each.
RANDOM, TOP, LOCAL = 500, 10, 10


def _cdf(z: np.ndarray) -> np.ndarray:
    return np.asarray([0.5 * (1 + math.erf(v / math.sqrt(2))) for v in z])


def expected_improvement(mean: np.ndarray, deviation: np.ndarray, best: float) -> np.ndarray:
    z = (best - mean) / deviation
    return (best - mean) * _cdf(z) + deviation * np.exp(-0.5 * z * z) / math.sqrt(2 * math.pi)


class Surrogate(Proposer):
    at = 0
    start = 8

    def model(self, x: np.ndarray, y: np.ndarray, candidates: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
        raise NotImplementedError

    def propose(self, slots: int, seen: Sequence[Observation]) -> list[Config]:
        out: list[Config] = []
        for _ in range(slots):
            out.append(self._one(seen, out))
            self.at += 1
        return out

    def explores(self) -> bool:
        return False

    def _one(self, seen: Sequence[Observation], pending: Sequence[Config]) -> Config:
        known = [o for o in seen if o.error is not None]
        if len(known) < self.start or self.explores():
            return self.space.draw(self.seed, self.at)
        rng = np.random.Generator(np.random.PCG64([self.seed, self.at]))
        best = min(o.error for o in known)
        # models still running stand in with the best error, so that a batch spreads out
        waiting = [o.config for o in seen if o.error is None] + list(pending)
        x = np.asarray([self.space.encode(c) for c in [o.config for o in known] + waiting])
        y = np.asarray([o.error for o in known] + [best] * len(waiting))
        pool = [self.space.draw(self.seed + 1 + self.at, i) for i in range(RANDOM)]
        for o in sorted(known, key=lambda o: o.error)[:TOP]:
            f = self.space.family(o.config.family)
            for _ in range(LOCAL):
                pool.append(f.config([min(1.0, max(0.0, u + rng.normal(0, 0.1))) for u in f.point(o.config)]))
        mean, deviation = self.model(x, y, np.asarray([self.space.encode(c) for c in pool]), rng)
        return pool[int(np.argmax(expected_improvement(mean, np.maximum(deviation, 1e-9), best)))]
