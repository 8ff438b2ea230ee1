"""Accuracy measures, learning curves and comparisons of plans."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def error(df: DataFrame, label: str = "label", prediction: str = "prediction") -> DataFrame:
    """error, accuracy and rows of predictions."""
    wrong = F.when(F.col(label) == F.col(prediction), 0.0).otherwise(1.0)
    return df.agg(F.avg(wrong).alias("error"), (1 - F.avg(wrong)).alias("accuracy"), F.count(F.lit(1)).alias("n"))


def confusion(df: DataFrame, label: str = "label", prediction: str = "prediction") -> DataFrame:
    return df.groupBy(label, prediction).agg(F.count(F.lit(1)).alias("n"))


def metrics(df: DataFrame, label: str = "label", prediction: str = "prediction", score: str | None = None) -> DataFrame:
    """Precision, recall, F1 and accuracy of class 1; log-loss when a probability is given."""
    hit = lambda y, p: F.sum(F.when((F.col(label) == y) & (F.col(prediction) == p), 1.0).otherwise(0.0))
    out = df.agg(hit(1, 1).alias("tp"), hit(0, 1).alias("fp"), hit(1, 0).alias("fn"), hit(0, 0).alias("tn"), *([F.avg(-F.when(F.col(label) == 1, F.ln(score)).otherwise(F.ln(1 - F.col(score)))).alias("log_loss")] if score else []))
    return out.select("*", F.expr("tp / nullif(tp + fp, 0)").alias("precision"), F.expr("tp / nullif(tp + fn, 0)").alias("recall"), F.expr("2 * tp / nullif(2 * tp + fp + fn, 0)").alias("f1"), F.expr("(tp + tn) / (tp + fp + fn + tn)").alias("accuracy"))


def mse(df: DataFrame, label: str = "label", prediction: str = "prediction") -> DataFrame:
    return df.agg(F.avg(F.pow(F.col(prediction) - F.col(label), 2)).alias("mse"), F.var_pop(label).alias("variance"))


def majority_error(df: DataFrame, label: str = "label") -> DataFrame:
    """Error of always saying the most frequent class."""
    return df.groupBy(label).agg(F.count(F.lit(1)).alias("n")).agg((1 - F.max("n") / F.sum("n")).alias("majority_error"), F.sum("n").alias("n"))


def curve(history: DataFrame, by: str = "seconds", run: str = "run_id") -> DataFrame:
    """Best error so far, by time or by number of evaluations."""
    w = Window.partitionBy(run).orderBy(by, "model_id").rowsBetween(Window.unboundedPreceding, 0)
    return history.withColumn("best_error", F.min(F.nanvl("valid_error", F.lit(None))).over(w))


def time_to(history: DataFrame, within: float, by: str = "seconds", run: str = "run_id") -> DataFrame:
    """First point at which a run is within (1 + within) of its own final best."""
    c = curve(history, by, run).withColumn("final", F.min(F.nanvl("valid_error", F.lit(None))).over(Window.partitionBy(run)))
    return c.filter(F.col("best_error") <= (1 + within) * F.col("final")).groupBy(run).agg(F.min(by).alias("reached"), F.min("final").alias("final_error"))


def scans_saved(iterations_with: int, iterations_without: int) -> float:
    return 1 - iterations_with / iterations_without


def retained_gain(baseline: float, with_bandit: float, without: float) -> float:
    """Share of the error reduction over the baseline that early stopping keeps."""
    return (baseline - with_bandit) / (baseline - without)


def p_value(test_error: float, baseline: float, n: int) -> float:
    """One-sided normal approximation: chance of so small an error at the baseline's rate."""
    spread = math.sqrt(max(baseline * (1 - baseline), 1e-12) / n)
    return 0.5 * math.erfc((baseline - test_error) / spread / math.sqrt(2))


def false_discovery(p_values: Sequence[float], level: float = 0.05) -> list[bool]:
    """Benjamini-Hochberg: which hypotheses are rejected."""
    order = sorted(range(len(p_values)), key=lambda i: p_values[i])
    last = max((k + 1 for k, i in enumerate(order) if p_values[i] <= level * (k + 1) / len(order)), default=0)
    kept = set(order[:last])
    return [i in kept for i in range(len(p_values))]


def false_discovery_table(df: DataFrame, level: float = 0.05) -> DataFrame:
    """The same rule on a table of few hypotheses (model_id, p)."""
    w = Window.orderBy("p", "model_id")
    ranked = df.withColumn("rank", F.row_number().over(w)).crossJoin(F.broadcast(df.agg(F.count(F.lit(1)).alias("m"))))
    cut = ranked.filter(F.col("p") <= level * F.col("rank") / F.col("m")).agg(F.coalesce(F.max("rank"), F.lit(0)).alias("cut"))
    return ranked.crossJoin(F.broadcast(cut)).select("model_id", "p", "rank", (F.col("rank") <= F.col("cut")).alias("rejected"))
