"""Model spaces: families with real, integer and categorical hyperparameters that exist only
under their family, and their image in the unit cube."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

from ..functions import draws


@dataclass(frozen=True)
class Real:
    lo: float
    hi: float
    log: bool = False
    categorical = False

    def decode(self, u: float) -> float:
        u = min(1.0, max(0.0, u))
        if self.log:
            return math.exp(math.log(self.lo) + u * (math.log(self.hi) - math.log(self.lo)))
        return self.lo + u * (self.hi - self.lo)

    def encode(self, v: float) -> float:
        if self.log:
            return (math.log(v) - math.log(self.lo)) / (math.log(self.hi) - math.log(self.lo))
        return (v - self.lo) / (self.hi - self.lo)


@dataclass(frozen=True)
class Integer:
    lo: int
    hi: int
    categorical = False

    def decode(self, u: float) -> int:
        return min(self.hi, self.lo + round(min(1.0, max(0.0, u)) * (self.hi - self.lo)))

    def encode(self, v: float) -> float:
        return (v - self.lo) / (self.hi - self.lo) if self.hi > self.lo else 0.0


@dataclass(frozen=True)
class Choice:
    options: tuple[str, ...]
    categorical = True

    def decode(self, u: float) -> str:
        return self.options[min(len(self.options) - 1, int(u * len(self.options)))]

    def encode(self, v: str) -> float:
        return (self.options.index(v) + 0.5) / len(self.options)


Parameter = Real | Integer | Choice


@dataclass(frozen=True)
class Config:
    family: str
    params: tuple[tuple[str, float | int | str], ...]

    def __getitem__(self, name: str) -> float | int | str:
        return dict(self.params)[name]

    def get(self, name: str, default: float | str | None = None):
        return dict(self.params).get(name, default)

    def row(self) -> dict:
        """As the struct (family, params, cats)."""
        return {"family": self.family, "params": {k: float(v) for k, v in self.params if not isinstance(v, str)}, "cats": {k: v for k, v in self.params if isinstance(v, str)}}


@dataclass(frozen=True)
class Family:
    name: str
    parameters: dict[str, Parameter] = field(default_factory=dict)

    def config(self, point: Sequence[float]) -> Config:
        return Config(self.name, tuple((k, p.decode(u)) for (k, p), u in zip(self.parameters.items(), point, strict=True)))

    def point(self, config: Config) -> list[float]:
        return [p.encode(config[k]) for k, p in self.parameters.items()]


@dataclass(frozen=True)
class ModelSpace:
    families: tuple[Family, ...]

    def family(self, name: str) -> Family:
        return next(f for f in self.families if f.name == name)

    def dimensions(self) -> int:
        """Family coordinate (when there is a choice) and every parameter of every family."""
        return (len(self.families) > 1) + sum(len(f.parameters) for f in self.families)

    def encode(self, config: Config) -> list[float]:
        """Unit-cube point; coordinates of inactive parameters are -1."""
        out: list[float] = []
        if len(self.families) > 1:
            out.append((self.families.index(self.family(config.family)) + 0.5) / len(self.families))
        for f in self.families:
            out += f.point(config) if f.name == config.family else [-1.0] * len(f.parameters)
        return out

    def decode(self, point: Sequence[float]) -> Config:
        at, k = 0, 0
        if len(self.families) > 1:
            k, at = min(len(self.families) - 1, int(point[0] * len(self.families))), 1
        for f in self.families[:k]:
            at += len(f.parameters)
        own = self.families[k]
        return own.config([min(1.0, max(0.0, u)) for u in point[at : at + len(own.parameters)]])

    def draw(self, seed: int, i: int) -> Config:
        """Configuration ``i`` of a seed, whatever else was asked for."""
        k = min(len(self.families) - 1, int(draws.uniform_value(f"{seed}:family", i) * len(self.families)))
        f = self.families[k]
        return f.config([draws.uniform_value(f"{seed}:{f.name}.{name}", i) for name in f.parameters])

    @property
    def categorical(self) -> bool:
        return any(p.categorical for f in self.families for p in f.parameters.values())


#: Published ranges of the search spaces (fixed values).
RATE, L2, NOISE = (1e-3, 1e1), (1e-4, 1e2), (1e-4, 1e2)
PROJECTION = (1, 10)


def random_feature_logistic(d: int) -> ModelSpace:
    return ModelSpace((Family("logistic_rff", {"rate": Real(*RATE, log=True), "l2": Real(*L2, log=True), "size": Integer(PROJECTION[0] * d, PROJECTION[1] * d), "noise": Real(*NOISE, log=True)}),))


def linear_pair() -> ModelSpace:
    own = {"rate": Real(*RATE, log=True), "l2": Real(*L2, log=True)}
    return ModelSpace((Family("svm", dict(own)), Family("logistic", dict(own))))


def kernel_svm() -> ModelSpace:
    own = {"scale": Real(1e-2, 1e1, log=True), "skew": Real(0.0, 1.0), "l2": Real(*L2, log=True)}
    return ModelSpace((Family("gaussian", dict(own)), Family("cauchy", dict(own))))


def component_pipeline(d: int) -> ModelSpace:
    """Two stages searched as one: the number of leading principal components, and the model on them."""
    own = {"components": Integer(1, d), "rate": Real(*RATE, log=True), "l2": Real(*L2, log=True)}
    return ModelSpace((Family("svm_components", dict(own)), Family("logistic_components", dict(own))))


def tiny() -> ModelSpace:
    return ModelSpace((Family("logistic", {"rate": Real(0.1, 1.0, log=True), "l2": Real(1e-4, 1e-2, log=True)}),))
