"""Independent uniform draws in the box (log box where a parameter says so)."""

from __future__ import annotations

from collections.abc import Sequence

from ..space import Config
from .base import Observation, Proposer, register


class Uniform(Proposer):
    at = 0

    def propose(self, slots: int, seen: Sequence[Observation]) -> list[Config]:
        out = [self.space.draw(self.seed, self.at + i) for i in range(slots)]
        self.at += slots
        return out


register("random", Uniform)
