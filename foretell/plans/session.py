"""Predictive sessions: the DataFrame form of predictive clauses.

``predict(df, target, predictors, given)`` finds a plan for the target from the labelled relation
(reused from the catalog when the same question was planned before) and adds it as a column.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.random_features import Components
from . import blocks as packed
from .bandit import Eliminator
from .budget import Budget
from .catalog import Catalog, fingerprint
from .planner import PlanResult, plan_adaptive
from .recommend import Recommender
from .score import Plan
from .space import Family, ModelSpace, Real, linear_pair
from .tasks import hashed_features, numeric_expressions, split_of, text_predictors, word_slots


class ClauseError(ValueError):
    """An attribute of a predictive clause that its relation does not have, or a nested clause."""


_WHOLE = ("tinyint", "smallint", "int", "bigint")


def infer_task(df: DataFrame, target: str, predictors: list[str] | None = None, identifiers: tuple[str, ...] = ()) -> str:
    """recommendation for a number that two ``identifiers`` predict (whole numbers that name things);
    regression for fractional targets, classification for all others."""
    kinds = dict(df.dtypes)
    number = kinds[target] in (*_WHOLE, "float", "double") or kinds[target].startswith("decimal")
    if number and predictors and len(predictors) == 2 and all(p in identifiers and kinds[p] in _WHOLE for p in predictors):
        return "recommendation"
    return "regression" if dict(df.dtypes)[target] in ("float", "double") or dict(df.dtypes)[target].startswith("decimal") else "classification"


def check_clause(target: str, predictors: list[str] | None, relation: DataFrame) -> None:
    """Target and predictors must all be columns of the training relation."""
    missing = {target, *(predictors or [])} - set(relation.columns)
    if missing:
        raise ClauseError(f"not in the training relation: {', '.join(sorted(missing))}")
    if predictors and target in predictors:
        raise ClauseError(f"{target} cannot predict itself")


@dataclass
class Session:
    """``key``: columns that identify rows and are never predictors.  ``identifiers``: columns that name
    users or items; a number that two of them predict is a recommendation.  ``most_classes``: a target
    with more values raises an error."""

    spark: SparkSession
    catalog: Catalog | None = None
    space: ModelSpace | None = None
    budget: Budget = field(default_factory=lambda: Budget(models=8))
    proposer: str = "parzen"
    partial_iters: int = 5
    max_iters: int = 20
    batch_size: int = 8
    key: tuple[str, ...] = ()
    identifiers: tuple[str, ...] = ()
    most_classes: int = 1000
    regime: str = "auto"
    seed: int = 0
    planned: int = 0
    last: PlanResult | None = None
    recommenders: dict[str, Recommender] = field(default_factory=dict)

    def plan(self, relation: DataFrame, target: str, predictors: list[str] | None = None, shared: list[str] | None = None, version: str = "") -> Plan:
        """Find or make the plan of a clause.  Omitted predictors: all columns of the relation
        but target and key that the scored relation (``shared``) has too."""
        check_clause(target, predictors, relation)
        named = predictors or [c for c in relation.columns if c != target and c not in self.key and (shared is None or c in shared)]
        mark = fingerprint(target, named, relation, version)
        if self.catalog and (found := self.catalog.lookup(mark)):
            return found
        plan = self._search(relation, target, named)
        if self.catalog:
            self.catalog.store(mark, plan)
        return plan

    def _search(self, relation: DataFrame, target: str, predictors: list[str]) -> Plan:
        self.planned += 1
        rows = relation.filter(F.col(target).isNotNull())
        task = infer_task(relation, target)
        expressions = numeric_expressions(rows, predictors)
        texts = [e for _, e in expressions]
        words = [word_slots(f"coalesce(`{p}`, '')") for p in text_predictors(rows, predictors)]
        values = [] if task == "regression" else [r[0] for r in rows.select(target).distinct().limit(self.most_classes + 1).collect()]
        if len(values) > self.most_classes:
            raise ClauseError(f"{target} has over {self.most_classes} classes")
        values = sorted(values, key=lambda v: (str(type(v)), v))
        wide = rows.select(F.xxhash64(*[F.col(p) for p in predictors]).cast("string").alias("key"), F.col(target).alias("_target"), *[F.expr(e).alias(f"x{i}") for i, e in enumerate(texts)], *[F.expr(e).alias(f"_t{i}") for i, e in enumerate(words)])
        stats = wide.agg(*[e for i in range(len(texts)) for e in (F.avg(f"x{i}"), F.stddev_pop(f"x{i}"))]).first()
        mean, scale = [float(stats[2 * i] or 0.0) for i in range(len(texts))], [float(stats[2 * i + 1] or 0.0) or 1.0 for i in range(len(texts))]
        label = F.col("_target").cast("double") if task == "regression" else (F.array_position(F.array(*[F.lit(v) for v in values]), F.col("_target")) - 1).cast("int")
        features = F.array(*[(F.coalesce(F.col(f"x{i}"), F.lit(m)) - F.lit(m)) / F.lit(s) for i, (m, s) in enumerate(zip(mean, scale, strict=True))])
        slots = [f"_t{i}" for i in range(len(words))]
        data = wide.select(split_of(F.col("key"), self.seed).alias("split"), label.alias("label"), features.cast("array<double>").alias("features"), *slots)
        data = hashed_features(data.withColumnRenamed("features", "_numbers"), ["split", "label"], "_numbers", slots) if words else data
        blocks = packed.store(packed.pack(data))
        if task == "regression":
            space = ModelSpace((Family("ridge", {"rate": Real(1e-2, 0.5, log=True), "l2": Real(1e-4, 1e-1, log=True)}),))
        else:
            space = self.space or linear_pair()
        classes = 1 if task == "regression" or len(values) <= 2 else len(values)
        prior = self.catalog.prior(space) if self.catalog else None
        self.last = r = plan_adaptive(blocks, space, self.budget, proposer=self.proposer, partial_iters=self.partial_iters, max_iters=self.max_iters, batch_size=self.batch_size, bandit=Eliminator(), classes=classes, seed=self.seed, prior=prior, regime=self.regime, step="adagrad" if words else "plain")
        packed.release(blocks)
        if r.column is None:
            raise ClauseError(f"no model of {target} could be trained")
        if self.catalog:
            self.catalog.remember(r)
        counts = [] if task == "regression" else [x["n"] for x in rows.groupBy(target).agg(F.count(F.lit(1)).alias("n")).collect()]
        c = r.column
        if isinstance(c.projection, Components):
            raise ClauseError("a plan on components is not stored; use a space without them")
        projection = None if c.projection is None else dict(c.projection.__dict__)
        names = [str(v) for v in values] if len(values) > 1 else [str(v) for v in [*values, *values]]
        return Plan(target, list(predictors), texts, mean, scale, c.weights.tolist(), names, c.family, task, projection, r.config.row()["params"], r.valid_error, r.test_error, 1 - max(counts) / sum(counts) if counts else float("nan"), r.ledger.as_dict(), dict(relation.dtypes)[target], words)

    def _recommender(self, given: DataFrame, target: str, predictors: list[str]) -> Recommender:
        mark = fingerprint(target, predictors, given)
        if mark not in self.recommenders:
            self.planned += 1
            self.recommenders[mark] = Recommender.fit(given, target, predictors, seed=self.seed)
        return self.recommenders[mark]

    def predict(self, df: DataFrame, target: str, predictors: list[str] | None = None, given: DataFrame | None = None, name: str | None = None) -> DataFrame:
        if given is None:
            raise ClauseError("a training relation is needed")
        if predictors and target in given.columns and infer_task(given, target, predictors, self.identifiers) == "recommendation":
            check_clause(target, predictors, given)
            return self._recommender(given, target, predictors).score(df, name or target)
        plan = self.plan(given, target, predictors, shared=df.columns)
        return df.withColumn(name or target, plan.column())
