"""Gradient descent as relational algebra: models x rows, one aggregation per iteration.

Rows are wide (x1..xd); models are a small table (id, family, rate, l2, w0..wd) that is broadcast.
Everything stays in generated JVM code.  ``training_sql`` writes the same iterations as nested
SELECTs for another engine.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Model:
    """One column of a batch: family 'logistic', 'svm' or 'ridge'."""

    model_id: int
    family: str
    rate: float
    l2: float


def weights(d: int) -> list[str]:
    return [f"w{i}" for i in range(d + 1)]


def models_table(spark: SparkSession, models: Sequence[Model], d: int) -> DataFrame:
    """All weights start at zero."""
    rows = [(m.model_id, m.family, m.rate, m.l2, *([0.0] * (d + 1))) for m in models]
    return spark.createDataFrame(rows, f"model_id int, family string, rate double, l2 double, {', '.join(f'{w} double' for w in weights(d))}")


def margin(names: Sequence[str]) -> Column:
    out = F.col("w0")
    for i, n in enumerate(names):
        out = out + F.col(f"w{i + 1}") * F.col(n)
    return out


def residual(z: Column) -> Column:
    """Derivative of each family's loss by the margin."""
    y = F.col("label").cast("double")
    sign = 2 * y - 1
    return (
        F.when(F.col("family") == "logistic", 1.0 / (1.0 + F.exp(-z)) - y)
        .when(F.col("family") == "svm", F.when(sign * z < 1, -sign).otherwise(0.0))
        .otherwise(z - y)
    )


def step(rows: DataFrame, models: DataFrame, names: Sequence[str]) -> DataFrame:
    """One full-gradient update of every model in one scan of ``rows``."""
    d = len(names)
    r = rows.crossJoin(F.broadcast(models)).withColumn("_r", residual(margin(names)))
    keys = ["model_id", "family", "rate", "l2", *weights(d)]
    grads = r.groupBy(*keys).agg(F.avg("_r").alias("_g0"), *[F.avg(F.col("_r") * F.col(n)).alias(f"_g{i + 1}") for i, n in enumerate(names)])
    new = [(F.col("w0") - F.col("rate") * F.col("_g0")).alias("w0")]
    new += [(F.col(f"w{i}") - F.col("rate") * (F.col(f"_g{i}") + F.col("l2") * F.col(f"w{i}"))).alias(f"w{i}") for i in range(1, d + 1)]
    return grads.select("model_id", "family", "rate", "l2", *new)


def train(rows: DataFrame, models: DataFrame, names: Sequence[str], iterations: int) -> DataFrame:
    """Iterations composed in one plan (for few iterations; the shared-scan trainer loops)."""
    for _ in range(iterations):
        models = step(rows, models, names)
    return models


def errors(rows: DataFrame, models: DataFrame, names: Sequence[str]) -> DataFrame:
    """model_id, valid_error, n over the given rows."""
    wrong = F.when((margin(names) > 0).cast("int") == F.col("label"), 0.0).otherwise(1.0)
    return rows.crossJoin(F.broadcast(models)).groupBy("model_id").agg(F.avg(wrong).alias("valid_error"), F.count(F.lit(1)).alias("n"))


def margin_sql(d: int) -> str:
    return " + ".join(["w0", *(f"w{i} * x{i}" for i in range(1, d + 1))])


#: What a step keeps besides the weights, as (first value, next value, next weight) in SQL: {a} is the kept
#: value, {g} the gradient, {w} the weight.
_STEPS = {
    "plain": ("0.0", "0.0", "{w} - rate * {g}"),
    "adagrad": ("1e-8", "{a} + {g} * {g}", "{w} - rate * {g} / sqrt({a} + {g} * {g})"),
    "nesterov": ("0.0", "0.9 * {a} - rate * {g}", "{w} + 0.9 * (0.9 * {a} - rate * {g}) - rate * {g}"),
}


def training_sql(rows_sql: str, models: Sequence[Model], d: int, iterations: int, where: str = "split = 'train'", step: str = "plain") -> str:
    """WITH clause (without the final SELECT): rows, and models after each iteration as m0, m1, ..."""
    if step != "plain":
        return _stepped_sql(rows_sql, models, d, iterations, where, step)
    values = ", ".join(f"({m.model_id}, '{m.family}', {m.rate!r}, {m.l2!r}, {', '.join(['0.0'] * (d + 1))})" for m in models)
    parts = [f"raw_rows AS MATERIALIZED ({rows_sql})", f"fit AS (SELECT * FROM raw_rows WHERE {where})"]
    parts.append(f"m0(model_id, family, rate, l2, {', '.join(weights(d))}) AS (SELECT col0, col1, col2::DOUBLE, col3::DOUBLE, {', '.join(f'col{i + 4}::DOUBLE' for i in range(d + 1))} FROM (VALUES {values}))")
    z = margin_sql(d)
    res = f"CASE family WHEN 'logistic' THEN 1.0 / (1.0 + exp(-({z}))) - label WHEN 'svm' THEN CASE WHEN (2 * label - 1) * ({z}) < 1 THEN -(2.0 * label - 1) ELSE 0.0 END ELSE ({z}) - label END"
    for t in range(iterations):
        keys = f"model_id, family, rate, l2, {', '.join(weights(d))}"
        grads = ", ".join(["avg(r) AS g0", *(f"avg(r * x{i}) AS g{i}" for i in range(1, d + 1))])
        new = ", ".join(["w0 - rate * g0 AS w0", *(f"w{i} - rate * (g{i} + l2 * w{i}) AS w{i}" for i in range(1, d + 1))])
        parts.append(f"m{t + 1} AS MATERIALIZED (SELECT model_id, family, rate, l2, {new} FROM (SELECT {keys}, {grads} FROM (SELECT *, {res} AS r FROM fit, m{t}) GROUP BY {keys}))")
    return "WITH " + ",\n".join(parts)


def _stepped_sql(rows_sql: str, models: Sequence[Model], d: int, iterations: int, where: str, step: str) -> str:
    """``training_sql`` with a step that keeps a value a0..ad beside every weight."""
    first, kept, moved = _STEPS[step]
    state = [*weights(d), *(f"a{i}" for i in range(d + 1))]
    values = ", ".join(f"({m.model_id}, '{m.family}', {m.rate!r}, {m.l2!r}, {', '.join(['0.0'] * (d + 1) + [first] * (d + 1))})" for m in models)
    parts = [f"raw_rows AS MATERIALIZED ({rows_sql})", f"fit AS (SELECT * FROM raw_rows WHERE {where})"]
    parts.append(f"m0(model_id, family, rate, l2, {', '.join(state)}) AS (SELECT col0, col1, col2::DOUBLE, col3::DOUBLE, {', '.join(f'col{i + 4}::DOUBLE' for i in range(len(state)))} FROM (VALUES {values}))")
    z = margin_sql(d)
    res = f"CASE family WHEN 'logistic' THEN 1.0 / (1.0 + exp(-({z}))) - label WHEN 'svm' THEN CASE WHEN (2 * label - 1) * ({z}) < 1 THEN -(2.0 * label - 1) ELSE 0.0 END ELSE ({z}) - label END"
    for t in range(iterations):
        keys = f"model_id, family, rate, l2, {', '.join(state)}"
        grads = ", ".join(["avg(r) AS g0", *(f"avg(r * x{i}) AS h{i}" for i in range(1, d + 1))])
        named = ", ".join([keys, "g0", *(f"h{i} + l2 * w{i} AS g{i}" for i in range(1, d + 1))])
        new = ", ".join([*(moved.format(a=f"a{i}", g=f"g{i}", w=f"w{i}") + f" AS w{i}" for i in range(d + 1)), *(kept.format(a=f"a{i}", g=f"g{i}") + f" AS a{i}" for i in range(d + 1))])
        parts.append(f"m{t + 1} AS MATERIALIZED (SELECT model_id, family, rate, l2, {new} FROM (SELECT {named} FROM (SELECT {keys}, {grads} FROM (SELECT *, {res} AS r FROM fit, m{t}) GROUP BY {keys})))")
    return "WITH " + ",\n".join(parts)


def errors_sql(models: str, d: int) -> str:
    """(model_id, valid_error, test_error) of a table of models over ``raw_rows``."""
    wrong = f"CASE WHEN (CASE WHEN {margin_sql(d)} > 0 THEN 1 ELSE 0 END) = label THEN 0.0 ELSE 1.0 END"
    return f"SELECT model_id, avg(CASE WHEN split = 'valid' THEN {wrong} END) AS valid_error, avg(CASE WHEN split = 'test' THEN {wrong} END) AS test_error FROM raw_rows, {models} GROUP BY model_id"
