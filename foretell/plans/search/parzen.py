"""Tree-structured Parzen estimator: sample where good configurations are dense, bad ones rare.

The family is chosen first, then the parameters that exist under it.  Models still running count
as bad, so a batch spreads out; models stopped early count with their last error.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

from ..space import Choice, Config, Parameter
from .base import Observation, Proposer, register

#: Published settings: share of good ones, random start, candidates per draw.
GOOD, START, CANDIDATES = 0.25, 20, 24


class _Density:
    """Mixture of truncated normals at the observations and a uniform prior, on the unit line."""

    def __init__(self, at: Sequence[float], parameter: Parameter):
        self.options = len(parameter.options) if isinstance(parameter, Choice) else 0
        if self.options:
            counts = np.ones(self.options)
            for u in at:
                counts[min(self.options - 1, int(u * self.options))] += 1
            self.share = counts / counts.sum()
            return
        self.at = np.sort(np.asarray([0.5, *at], float))
        edges = np.concatenate(([0.0], self.at, [1.0]))
        self.width = np.clip(np.maximum(np.diff(edges)[:-1], np.diff(edges)[1:]), 1.0 / (1 + len(self.at)), 1.0)

    def sample(self, rng: np.random.Generator) -> float:
        if self.options:
            return (rng.choice(self.options, p=self.share) + 0.5) / self.options
        while True:
            k = rng.integers(len(self.at) + 1)
            u = rng.random() if k == len(self.at) else rng.normal(self.at[k], self.width[k])
            if 0 <= u <= 1:
                return float(u)

    def log(self, u: float) -> float:
        if self.options:
            return float(np.log(self.share[min(self.options - 1, int(u * self.options))]))
        bell = np.exp(-0.5 * ((u - self.at) / self.width) ** 2) / (self.width * np.sqrt(2 * np.pi))
        return float(np.log((bell.sum() + 1.0) / (len(self.at) + 1)))


class Parzen(Proposer):
    at = 0

    def propose(self, slots: int, seen: Sequence[Observation]) -> list[Config]:
        out: list[Config] = []
        for _ in range(slots):
            out.append(self._one(seen, out))
            self.at += 1
        return out

    def _one(self, seen: Sequence[Observation], pending: Sequence[Config]) -> Config:
        known = sorted((o for o in seen if o.error is not None), key=lambda o: o.error)
        if len(known) < min(START, max(2, self.budget // 2)):
            return self.space.draw(self.seed, self.at)
        rng = np.random.Generator(np.random.PCG64([self.seed, self.at]))
        cut = max(1, int(np.ceil(GOOD * len(known))))
        good, bad = [o.config for o in known[:cut]], [o.config for o in known[cut:]] + [o.config for o in seen if o.error is None] + list(pending)
        names = [f.name for f in self.space.families]
        share = np.asarray([1.0 + sum(c.family == n for c in good) for n in names])
        rest = np.asarray([1.0 + sum(c.family == n for c in bad) for n in names])
        best: tuple[float, Config] | None = None
        for _ in range(CANDIDATES):
            k = int(rng.choice(len(names), p=share / share.sum()))
            f = self.space.families[k]
            score = float(np.log(share[k] / share.sum()) - np.log(rest[k] / rest.sum()))
            point = []
            for name, p in f.parameters.items():
                near = _Density([p.encode(c[name]) for c in good if c.family == f.name], p)
                far = _Density([p.encode(c[name]) for c in bad if c.family == f.name], p)
                u = near.sample(rng)
                point.append(u)
                score += near.log(u) - far.log(u)
            if best is None or score > best[0]:
                best = (score, f.config(point))
        return best[1]


register("parzen", Parzen)
