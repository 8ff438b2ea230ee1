"""Bandit allocation: which partially trained models go on."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass
class Trial:
    """One model's progress.  ``quality`` is 1 - validation error, NaN when it diverged."""

    model_id: int
    iterations: int
    quality: float
    finished: bool = False


@dataclass
class Verdict:
    finished: list[Trial]
    active: list[Trial]
    dropped: list[Trial]


@dataclass
class Eliminator:
    """Keep a model while its quality, raised by the slack, exceeds the best seen (``quality``),
    or while its error is within the slack of the least error (``error``).

    ``check``: 'every_round' or 'once' (only at a model's first stop).  ``include_current``: let
    the models just advanced count for the best; by default only earlier rounds do, so the first
    round drops nothing.  ``tie``: added to both sides of the error rule (1 / validation rows), so
    that a perfect model does not end all others.
    """

    slack: float = 0.5
    rule: str = "quality"
    check: str = "every_round"
    include_current: bool = False
    tie: float = 0.0
    _seen: set[int] = field(default_factory=set)

    def keeps(self, quality: float, best: float) -> bool:
        if math.isnan(quality):
            return False
        if self.rule == "quality":
            return quality * (1 + self.slack) > best
        return (1 - quality) + self.tie <= (1 + self.slack) * ((1 - best) + self.tie)

    def sort(self, advanced: Sequence[Trial], earlier: Sequence[float]) -> Verdict:
        """``earlier``: qualities observed in former rounds."""
        pool = [q for q in earlier if not math.isnan(q)]
        if self.include_current:
            pool += [t.quality for t in advanced if not math.isnan(t.quality)]
        best = max(pool, default=None)
        out = Verdict([], [], [])
        for t in advanced:
            judged = self.check == "every_round" or t.model_id not in self._seen
            self._seen.add(t.model_id)
            if t.finished:
                out.finished.append(t)
            elif math.isnan(t.quality) or (judged and best is not None and not self.keeps(t.quality, best)):
                out.dropped.append(t)
            else:
                out.active.append(t)
        return out


@dataclass
class SuccessiveHalving:
    """Another allocation rule: of the models at one stop keep the best share."""

    share: float = 0.5

    def sort(self, advanced: Sequence[Trial], earlier: Sequence[float]) -> Verdict:
        finished = [t for t in advanced if t.finished]
        rest = sorted((t for t in advanced if not t.finished and not math.isnan(t.quality)), key=lambda t: (-t.quality, t.model_id))
        kept = {t.model_id for t in rest[: max(1, math.ceil(len(rest) * self.share))]}
        return Verdict(finished, [t for t in advanced if t.model_id in kept], [t for t in advanced if not t.finished and t.model_id not in kept])


class FixedArms:
    """A fixed set of arms, one pull a round, chosen by upper confidence bounds."""

    def __init__(self, arms: int, exploration: float = 2.0):
        self.pulls, self.sums, self.exploration = [0] * arms, [0.0] * arms, exploration

    def choose(self) -> int:
        if 0 in self.pulls:
            return self.pulls.index(0)
        t = sum(self.pulls)
        scores = [s / n + math.sqrt(self.exploration * math.log(t) / n) for s, n in zip(self.sums, self.pulls, strict=True)]
        return max(range(len(scores)), key=lambda k: (scores[k], -k))

    def reward(self, arm: int, value: float) -> None:
        self.pulls[arm] += 1
        self.sums[arm] += value


def eliminate(models: DataFrame, history: DataFrame, *, slack: float = 0.5, rule: str = "quality", max_iterations: int = 100) -> DataFrame:
    """The same rule on tables: ``models`` with a column ``verdict``; the best is one broadcast row."""
    best = history.agg(F.max(F.nanvl("quality", F.lit(None))).alias("best"))
    q, b = F.col("quality"), F.col("best")
    fits = (q * (1 + slack) > b) if rule == "quality" else ((1 - q) <= (1 + slack) * (1 - b))
    verdict = F.when(F.isnan(q), "dropped").when(F.col("iters_done") >= max_iterations, "finished").when(b.isNull() | fits, "active").otherwise("dropped")
    return models.crossJoin(F.broadcast(best)).withColumn("verdict", verdict).drop("best")
