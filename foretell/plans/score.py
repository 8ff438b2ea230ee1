"""Plans as expressions: a trained model compiled to a Catalyst column, or to an Arrow function
when it is wide or lives on random features."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..operators.random_features import Projection
from ..operators.shared_scan import with_bias
from .tasks import SLOTS, WORD_SCALE

#: Features up to which a plan becomes a sum of products inside generated code.
INLINE = 64
#: Weights of words up to which they are looked up in generated code.
INLINE_SLOTS = 4096


def _looked_up(slots: Column, table: Column) -> Column:
    return F.aggregate(slots, F.lit(0.0), lambda a, s: a + F.element_at(table, s + 1))


@dataclass
class Plan:
    """What is stored: predictors as SQL expressions, standardisation, weights, classes."""

    target: str
    predictors: list[str]
    expressions: list[str]
    mean: list[float]
    scale: list[float]
    weights: list[list[float]]
    classes: list[str]
    family: str = "logistic"
    task: str = "classification"
    projection: dict | None = None
    params: dict[str, float] = field(default_factory=dict)
    valid_error: float = float("nan")
    test_error: float = float("nan")
    baseline_error: float = float("nan")
    ledger: dict[str, float] = field(default_factory=dict)
    label_type: str = "string"
    #: SQL expressions of the word slots of text predictors, and slots of each.
    texts: list[str] = field(default_factory=list)
    slots: int = SLOTS

    def to_json(self) -> str:
        return json.dumps(self.__dict__, sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> Plan:
        return cls(**json.loads(text))

    def inputs(self) -> list[Column]:
        return [(F.coalesce(F.expr(e).cast("double"), F.lit(m)) - F.lit(m)) / F.lit(s) for e, m, s in zip(self.expressions, self.mean, self.scale, strict=True)]

    def margins(self, words: list[Column] | None = None) -> list[Column]:
        """One expression per weight column; ``words``: the word slots of the text predictors."""
        w = np.asarray(self.weights)
        x = self.inputs()
        out = []
        for k in range(w.shape[1]):
            z = F.lit(float(w[0, k]))
            for i, c in enumerate(x):
                z = z + F.lit(float(w[i + 1, k])) * c
            for t, own in enumerate(words or []):
                first = 1 + len(x) + t * self.slots
                # one literal; an array of literals would be put together again for every word
                table = F.lit(np.ascontiguousarray(w[first : first + self.slots, k]))
                # the words' weights, looked up one by one: no vector of all slots is made
                z = z + _looked_up(own, table) * F.lit(WORD_SCALE) / F.greatest(F.lit(1), F.size(own))
            out.append(z)
        return out

    def column(self) -> Column:
        """The predicted attribute."""
        classes = len(self.weights[0])
        if self.projection is None and len(self.expressions) * classes <= INLINE and len(self.texts) * self.slots * classes <= INLINE_SLOTS:
            if not self.texts:
                return self._labelled(self.margins())
            # word slots stand once in the expression, whatever the number of classes
            words = F.array(F.struct(*[F.expr(e).alias(f"t{i}") for i, e in enumerate(self.texts)]))
            return F.element_at(F.transform(words, lambda s: self._labelled(self.margins([s[f"t{i}"] for i in range(len(self.texts))]))), 1)
        return self._arrow()

    def _labelled(self, margins: list[Column]) -> Column:
        if self.task == "regression":
            return margins[0]
        names = [F.lit(c).cast(self.label_type) for c in self.classes]
        if len(margins) == 1:
            return F.when(margins[0] > 0, names[1]).otherwise(names[0])
        # the margins stand once in the expression
        place = F.transform(F.array(F.array(*margins)), lambda m: F.array_position(m, F.array_max(m)))
        return F.element_at(F.array(*names), F.element_at(place, 1).cast("int"))

    def _arrow(self) -> Column:
        w, p, regression = np.asarray(self.weights), Projection(**self.projection) if self.projection else None, self.task == "regression"
        spark_weights = (w, p)

        slots = self.slots

        @pandas_udf("double")
        def score(batches: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.Series]:
            weights, projection = spark_weights
            drawn = projection.matrix() if projection else None
            for features, *words in batches:
                x = np.stack(features.to_numpy()) if len(features) else np.zeros((0, 1))
                for own in words:
                    sizes = own.map(len).to_numpy()
                    place = np.repeat(np.arange(len(own)), sizes) * slots + (np.concatenate(own.to_numpy()) if sizes.sum() else np.empty(0, int))
                    counts = np.bincount(place.astype(np.int64), minlength=len(own) * slots).reshape(len(own), slots)
                    x = np.hstack((x, WORD_SCALE * counts / np.maximum(1, sizes)[:, None]))
                x = projection.apply(x, *drawn) if projection and len(features) else x
                if not len(features):
                    yield pd.Series([], dtype=float)
                    continue
                m = with_bias(x) @ weights
                yield pd.Series(m[:, 0] if regression else ((m[:, 0] > 0).astype(float) if m.shape[1] == 1 else m.argmax(axis=1).astype(float)))

        value = score(F.array(*self.inputs()).cast("array<double>"), *[F.expr(e) for e in self.texts])
        if regression:
            return value
        return F.element_at(F.array(*[F.lit(c).cast(self.label_type) for c in self.classes]), value.cast("int") + 1)


def score(df: DataFrame, plan: Plan, name: str | None = None) -> DataFrame:
    return df.withColumn(name or plan.target, plan.column())
