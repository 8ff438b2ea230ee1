from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from ..space import Config, ModelSpace


@dataclass(frozen=True)
class Observation:
    """What a proposer may know of a model: its configuration and error (None while it runs)."""

    config: Config
    error: float | None


class Proposer:
    """Asked for at most ``slots`` configurations, given all observations so far.

    ``supports_categorical`` is false for methods that need a continuous box: they are run for
    one family at a time and refuse categorical parameters.
    """

    supports_categorical = True

    def __init__(self, space: ModelSpace, budget: int, seed: int = 0):
        self.space, self.budget, self.seed = space, budget, seed
        if space.categorical and not self.supports_categorical:
            raise ValueError(f"{type(self).__name__} does not take categorical parameters")

    def propose(self, slots: int, seen: Sequence[Observation]) -> list[Config]:
        raise NotImplementedError


_KNOWN: dict[str, Callable[..., Proposer]] = {}


def register(name: str, make_one: Callable[..., Proposer]) -> None:
    _KNOWN[name] = make_one


def make(name: str, space: ModelSpace, budget: int, seed: int = 0) -> Proposer:
    return _KNOWN[name](space, budget, seed)
