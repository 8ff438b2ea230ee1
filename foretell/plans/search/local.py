"""Common part of the two derivative-free local methods.

Each family of the space gets its own generator-driven search; points outside the unit cube are
not trained but answered with a penalty.  A generator yields a list of points and is sent their
errors; what it asks for at once fills the free slots.
"""

from __future__ import annotations

from collections.abc import Generator, Sequence

from ...functions import draws
from ..space import Config, Family
from .base import Observation, Proposer

Points = list[list[float]]
Search = Generator[Points, list[float], None]


def penalty(point: Sequence[float]) -> float:
    """Above 1 for points outside the cube (an error is at most 1), 0 inside."""
    out = sum(max(0.0, -u) + max(0.0, u - 1.0) for u in point)
    return 1.0 + out if out > 0 else 0.0


class LocalSearch(Proposer):
    supports_categorical = False

    def __init__(self, space, budget, seed=0):
        super().__init__(space, budget, seed)
        self.runs = [(f, self.search(f, k)) for k, f in enumerate(space.families)]
        self.waiting: list[dict] = []
        for f, g in self.runs:
            self._ask(f, g, next(g))
        self.turn = 0

    def search(self, family: Family, k: int) -> Search:
        raise NotImplementedError

    def start(self, k: int, restart: int, dims: int) -> list[float]:
        return [draws.uniform_value(f"{self.seed}:start:{k}:{restart}", i) for i in range(dims)]

    def _ask(self, family: Family, generator: Search, points: Points) -> None:
        errors: list[float | None] = [penalty(p) or None for p in points]
        self.waiting.append({"family": family, "run": generator, "points": points, "errors": errors, "configs": [None if e else family.config(p) for p, e in zip(points, errors, strict=True)], "sent": [e is not None for e in errors]})

    def _advance(self, seen: Sequence[Observation]) -> None:
        known = {o.config: o.error for o in seen if o.error is not None}
        moved = True
        while moved:
            moved = False
            for w in list(self.waiting):
                for i, c in enumerate(w["configs"]):
                    if w["errors"][i] is None and c in known:
                        w["errors"][i] = known[c]
                if all(e is not None for e in w["errors"]):
                    self.waiting.remove(w)
                    try:
                        self._ask(w["family"], w["run"], w["run"].send(w["errors"]))
                        moved = True
                    except StopIteration:
                        pass

    def propose(self, slots: int, seen: Sequence[Observation]) -> list[Config]:
        self._advance(seen)
        out: list[Config] = []
        tried = {o.config for o in seen}
        for w in self.waiting:
            for i, c in enumerate(w["configs"]):
                if len(out) < slots and not w["sent"][i]:
                    w["sent"][i] = True
                    if c not in tried and c not in out:
                        out.append(c)
        return out
