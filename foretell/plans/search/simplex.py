"""Simplex search with reflection, expansion, contraction and shrinking.

The four candidate moves of a step are asked for at once, so a batch is filled where a
sequential search would wait.
"""

from __future__ import annotations

from ..space import Family
from .base import register
from .local import LocalSearch, Search

#: Published coefficients of the moves, the edge of the first simplex, the spread at which it restarts.
REFLECT, EXPAND, CONTRACT, SHRINK = 1.0, 2.0, 0.5, 0.5
EDGE, SPREAD = 0.25, 1e-3


class Simplex(LocalSearch):
    def search(self, family: Family, k: int) -> Search:
        dims, restart = len(family.parameters), 0
        while True:
            first = self.start(k, restart, dims)
            points = [first] + [[u + (EDGE if u < 0.5 else -EDGE) * (i == j) for j, u in enumerate(first)] for i in range(dims)]
            errors = yield points
            corners = sorted(zip(errors, points, strict=True))
            for _ in range(200):
                if max(max(abs(a - b) for a, b in zip(p, corners[0][1], strict=True)) for _, p in corners[1:]) < SPREAD:
                    break
                worst, middle = corners[-1], [sum(p[i] for _, p in corners[:-1]) / dims for i in range(dims)]

                def along(t: float, middle=middle, worst=worst) -> list[float]:
                    return [m + t * (m - w) for m, w in zip(middle, worst[1], strict=True)]

                moves = [along(REFLECT), along(EXPAND), along(CONTRACT), along(-CONTRACT)]
                r, e, outer, inner = yield moves
                if r < corners[0][0]:
                    new = (e, moves[1]) if e < r else (r, moves[0])
                elif r < corners[-2][0]:
                    new = (r, moves[0])
                elif outer <= r < worst[0]:
                    new = (outer, moves[2])
                elif inner < worst[0]:
                    new = (inner, moves[3])
                else:
                    best = corners[0][1]
                    shrunk = [[b + SHRINK * (u - b) for u, b in zip(p, best, strict=True)] for _, p in corners[1:]]
                    errors = yield shrunk
                    corners = sorted([corners[0], *zip(errors, shrunk, strict=True)])
                    continue
                corners = sorted([*corners[:-1], new])
            restart += 1


register("simplex", Simplex)
