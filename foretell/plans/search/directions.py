"""Direction-set search: line searches along changing directions."""

from __future__ import annotations

import math

from ..space import Family
from .base import register
from .local import LocalSearch, Search

#: Probes of one bracket, golden-section refinements of a line, and the share of gold.
BRACKET, REFINE = (-0.5, -0.2, 0.2, 0.5), 2
GOLD = (math.sqrt(5) - 1) / 2


class Directions(LocalSearch):
    def search(self, family: Family, k: int) -> Search:
        dims = len(family.parameters)
        restart = 0
        while True:
            here = self.start(k, restart, dims)
            (value,) = yield [here]
            axes = [[1.0 if i == j else 0.0 for i in range(dims)] for j in range(dims)]
            while True:
                origin, first, drops = here, value, []
                for axis in axes:
                    before = value
                    steps = list(BRACKET)
                    errors = yield [[h + s * a for h, a in zip(here, axis, strict=True)] for s in steps]
                    tried = sorted([(0.0, value), *zip(steps, errors, strict=True)])
                    best = min(range(len(tried)), key=lambda i: (tried[i][1], abs(tried[i][0])))
                    lo, hi = tried[max(0, best - 1)][0], tried[min(len(tried) - 1, best + 1)][0]
                    at, low = tried[best]
                    for _ in range(REFINE):
                        probes = [hi - GOLD * (hi - lo), lo + GOLD * (hi - lo)]
                        errors = yield [[h + s * a for h, a in zip(here, axis, strict=True)] for s in probes]
                        if errors[0] <= errors[1]:
                            hi = probes[1]
                        else:
                            lo = probes[0]
                        for s, e in zip(probes, errors, strict=True):
                            if e < low:
                                at, low = s, e
                    here, value = [h + at * a for h, a in zip(here, axis, strict=True)], low
                    drops.append(before - value)
                if first - value <= 1e-9:
                    break
                moved = [h - o for h, o in zip(here, origin, strict=True)]
                size = math.sqrt(sum(m * m for m in moved))
                if size > 1e-9:
                    axes[max(range(dims), key=lambda i: drops[i])] = [m / size for m in moved]
            restart += 1


register("directions", Directions)
