"""Plans on streams: stateless scoring, windowed error on late labels, duplicates, drift.

Every runner processes what is available and stops (``availableNow``); the same DataFrames can be
started with any other trigger.  State is bounded by watermarks.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.score import Plan, score
from ..sources.tables import shared_dir, table


def read_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table (one file, or a folder of files) as a file stream, with the schema of the stored
    table; times without a zone become times of the session's zone, as watermarks need them."""
    stored = table(spark, sf_dir, name)
    reader = spark.readStream.schema(stored.schema)
    if any(f.endswith(f"/{name}.parquet") for f in stored.inputFiles()):
        out = reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    else:
        out = reader.parquet(f"{sf_dir}/{name}.parquet")
    return out.select(*[F.col(c).cast("timestamp").alias(c) if t == "timestamp_ntz" else F.col(c) for c, t in stored.dtypes])


def run_now(df: DataFrame, mode: str = "append") -> DataFrame:
    """Process all available rows into files of the shared folder and return them.

    Complete and update results are written per batch; the last batch holds."""
    spark = df.sparkSession
    where = f"{shared_dir(spark)}/foretell-stream-{uuid.uuid4().hex}"
    writer = df.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{where}/checkpoint")
    if mode == "append":
        query = writer.outputMode("append").format("parquet").option("path", f"{where}/rows").start()
    else:
        query = writer.outputMode(mode).foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{where}/rows")).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{where}/rows")


def score_stream(stream: DataFrame, plan: Plan, name: str = "prediction") -> DataFrame:
    """Arriving rows with the predicted attribute: no state."""
    return score(stream, plan, name)


def windowed_counts(stream: DataFrame, time: str, by: str, width: str, slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Rows and mean value per window and group; rows later than ``late`` are dropped."""
    window = F.window(time, width, slide) if slide else F.window(time, width)
    return stream.withWatermark(time, late).groupBy(window, by).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean"))


def judged_scores(scores: DataFrame, labels: DataFrame, key: str, late: str = "7 days") -> DataFrame:
    """Scores with the labels that arrive within ``late``: a stream-stream interval join.

    scores: key, scored (timestamp), prediction; labels: key, labelled (timestamp), label."""
    s = scores.withWatermark("scored", late)
    right = labels.withColumnRenamed(key, "_key").withWatermark("labelled", late)
    near = F.expr(f"_key = {key} AND labelled >= scored AND labelled <= scored + interval {late}")
    return s.join(right, near).select(key, "scored", "prediction", "label")


def windowed_error(judged: DataFrame, width: str = "1 day") -> DataFrame:
    """Error per window of judged scores (a stream in append mode with its watermark, or rows)."""
    return judged.groupBy(F.window("scored", width)).agg(F.avg((F.col("prediction") != F.col("label")).cast("double")).alias("error"), F.count(F.lit(1)).alias("n"))


def first_only(stream: DataFrame, time: str, keys: list[str], late: str = "1 day") -> DataFrame:
    """Repeated rows within the watermark dropped."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def drift(stream: DataFrame, by: str, value: str, threshold: float = 3.0) -> DataFrame:
    """Running mean and deviation per group and how many later values lie beyond ``threshold``
    deviations; the state is four numbers a group."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, mean, m2, out = state.get if state.exists else (0, 0.0, 0.0, 0)
        for frame in frames:
            for x in frame[value]:
                spread = (m2 / n) ** 0.5 if n > 1 else 0.0
                if n >= 30 and spread > 0 and abs(x - mean) > threshold * spread:
                    out += 1
                n += 1
                gap = x - mean
                mean += gap / n
                m2 += gap * (x - mean)
        state.update((n, mean, m2, out))
        yield pd.DataFrame({by: [key[0]], "n": [n], "mean": [mean], "deviation": [(m2 / n) ** 0.5 if n else 0.0], "drifted": [out]})

    return stream.select(by, value).groupBy(by).applyInPandasWithState(update, f"{by} string, n long, mean double, deviation double, drifted long", "n long, mean double, m2 double, drifted long", "update", GroupStateTimeout.NoTimeout)
