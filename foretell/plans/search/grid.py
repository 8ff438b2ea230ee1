"""Evenly spaced points, both ends included, on each parameter's own scale."""

from __future__ import annotations

import itertools
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..space import Choice, Config, ModelSpace
from .base import Observation, Proposer, register


def points_per_dimension(budget: int, dimensions: int) -> int:
    """Largest m >= 2 with m ** dimensions <= budget (2 when there is none)."""
    m = 2
    while (m + 1) ** max(1, dimensions) <= budget:
        m += 1
    return m


def grid(space: ModelSpace, budget: int) -> list[Config]:
    out = []
    share = budget // len(space.families)
    for f in space.families:
        free = [p for p in f.parameters.values() if not isinstance(p, Choice)]
        fixed = 1
        for p in f.parameters.values():
            fixed *= len(p.options) if isinstance(p, Choice) else 1
        m = points_per_dimension(max(1, share // fixed), len(free))
        axes = [[(i + 0.5) / len(p.options) for i in range(len(p.options))] if isinstance(p, Choice) else [i / (m - 1) for i in range(m)] for p in f.parameters.values()]
        out += [f.config(point) for point in itertools.product(*axes)]
    return out


def grid_table(spark: SparkSession, n: int, names: Sequence[str], lows: Sequence[float], highs: Sequence[float]) -> DataFrame:
    """The n ** D points of one family on log axes, made by the engine."""
    out = spark.range(1).select(F.lit(0).alias("_one"))
    for name, lo, hi in zip(names, lows, highs, strict=True):
        axis = F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("_i")
        out = out.select("*", axis).withColumn(name, F.exp(F.ln(F.lit(lo)) + F.col("_i") / F.lit(float(n - 1)) * (F.ln(F.lit(hi)) - F.ln(F.lit(lo))))).drop("_i")
    return out.drop("_one")


class Grid(Proposer):
    def __init__(self, space: ModelSpace, budget: int, seed: int = 0):
        super().__init__(space, budget, seed)
        self.points, self.at = grid(space, budget), 0

    def propose(self, slots: int, seen: Sequence[Observation]) -> list[Config]:
        out = self.points[self.at : self.at + slots]
        self.at += len(out)
        return out


register("grid", Grid)
