"""Experiments as entries: a table of figures each, and a table of what must hold, checked by SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import draws
from ..plans import experiments as X
from ..plans import tasks
from .registry import entry, r6

Spark = SparkSession
_ITERATIONS, _EVERY = 50, 5


def _majority_sql(name: str) -> str:
    """Majority error of the sample that an experiment draws from a task."""
    rows = f"({tasks.task_sql(tasks.TASKS[name])})"
    share = f"(SELECT least(1.0, {X.ROWS} / greatest(1, count(*))) FROM {rows})"
    return f"SELECT '{name}' AS task, round(1 - max(n) / sum(n), 6) AS majority_error FROM (SELECT label, count(*) AS n FROM {rows} WHERE {draws.uniform_sql('sample:0', 'key')} < {share} GROUP BY label)"


_BASE = " UNION ALL ".join(_majority_sql(t) for t in X.TASKS)


def _searches(spark: Spark, d: str) -> DataFrame:
    return X.compare_searches(spark, X.read_samples(spark, d))


@entry("search_errors")
def search_errors(spark: Spark, d: str) -> DataFrame:
    """Five tasks, seven methods, budgets 16 and 81: least validation error."""
    return _searches(spark, d)


@entry("bench_search", f"SELECT task, majority_error, CAST(budget AS INT) AS budget, CAST(7 AS BIGINT) AS methods, TRUE AS best_beats_chance, TRUE AS no_worse_with_more FROM ({_BASE}), (VALUES (16), (81)) b(budget)")
def bench_search(spark: Spark, d: str) -> DataFrame:
    """What holds of the search experiment: the best method's model errs on fewer than half of the
    validation rows, and no method but the grid is worse with the larger budget."""
    found = spark.createDataFrame(_searches(spark, d).toPandas())  # a row a search
    small = found.filter("budget = 16").select("task", "method", F.col("valid_error").alias("small"))
    joined = found.join(small, ["task", "method"])
    fine = F.min("valid_error") < 0.5
    more = F.bool_and((F.col("method") == "grid") | (F.col("valid_error") <= F.col("small")))
    return joined.groupBy("task", r6("majority_error").alias("majority_error"), "budget").agg(F.count(F.lit(1)).alias("methods"), fine.alias("best_beats_chance"), more.alias("no_worse_with_more"))


def bandit_rows(spark: Spark, d: str, models: int = 60, iterations: int = _ITERATIONS, every: int = _EVERY) -> list[dict]:
    samples = X.read_samples(spark, d)
    return X.compare_rules(samples, X.curves(spark, samples, models=models, iterations=iterations, every=every), iterations=iterations, every=every)


@entry("bandit_figures")
def bandit_figures(spark: Spark, d: str) -> DataFrame:
    """Five tasks without a rule, with the quality rule and with the error rule: what is saved and kept."""
    return spark.createDataFrame([tuple(r.values()) for r in bandit_rows(spark, d)], "task string, rule string, models int, iterations int, saved double, dropped double, error double, majority_error double, kept_gain double")


@entry("bench_bandit", f"SELECT task, rule, majority_error, CAST(60 AS INT) AS models, TRUE AS saves_what_it_drops, TRUE AS gain_kept_on_four FROM ({_BASE}), (VALUES ('none'), ('quality'), ('error')) r(rule)")
def bench_bandit(spark: Spark, d: str) -> DataFrame:
    """What holds of the bandit experiment: the share of iterations saved is at most 0.9 of the share of
    models dropped (a model runs to its first stop), at least half of that; and on four of the five sets or more at least 0.85 of the gain over the
    majority class is kept (on one, a slow starter that would have won in the end is dropped)."""
    rows, found = [], bandit_rows(spark, d)
    for r in found:
        kept = sum(o["kept_gain"] >= 0.85 for o in found if o["rule"] == r["rule"])
        cap = (1 - _EVERY / _ITERATIONS) * r["dropped"]
        rows.append((r["task"], r["rule"], round(r["majority_error"], 6) + 0.0, r["models"], bool(cap / 2 <= r["saved"] + 1e-9 and r["saved"] <= cap + 1e-9), kept >= 4))
    return spark.createDataFrame(rows, "task string, rule string, majority_error double, models int, saves_what_it_drops boolean, gain_kept_on_four boolean")
