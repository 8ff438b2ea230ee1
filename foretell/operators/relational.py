"""Joins and windows that a training relation needs and that have no one-word form in Spark."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, by: Sequence[str], left_time: str, right_time: str, values: Sequence[str]) -> DataFrame:
    """``left`` with the values of the last right row of the same key at or before its time.

    One union and one window per key instead of a range join; ties of the right side go to the
    greatest values.  Left columns must not be named like ``values``.
    """
    keep = [c for c in left.columns if c not in by]
    a = left.select(*by, F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.struct(*keep).alias("_left"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("_right"))
    b = right.select(*by, F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.lit(None).cast(left.select(F.struct(*keep)).schema[0].dataType).alias("_left"), F.struct(*values).alias("_right"))
    w = Window.partitionBy(*by).orderBy("_t", "_side", "_right").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_last", F.last("_right", ignorenulls=True).over(w)).filter("_side = 1")
    return both.select(*by, "_left.*", *[F.col(f"_last.{v}").alias(v) for v in values])


def interval_join(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of equal key with the right time in (left time - seconds, left time].

    Times are cut into buckets as wide as the interval, so each left row meets two buckets of its
    key by equality and the range is checked inside.
    """
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("_b", F.explode(F.array(bucket(left_time), bucket(left_time) - 1)))
    b = right.withColumn("_b", bucket(right_time)).withColumnRenamed(by, "_by")
    near = (F.col(right_time) <= F.col(left_time)) & (F.unix_timestamp(left_time) - F.unix_timestamp(right_time) < seconds)
    return a.join(b, (a["_b"] == b["_b"]) & (F.col(by) == F.col("_by")) & near).drop("_b", "_by")


def trailing(df: DataFrame, by: str, time: Column, value: str, seconds: int) -> DataFrame:
    """Every row with ``_n`` and ``_sum``, ``_values``: the rows of its key whose time, in whole seconds, is
    at most ``seconds`` before its own and not after it, and the sum and number of their values.

    Times are cut into blocks as long as the range.  What a row sees is the start of its own block and
    the end of the block before, so every row is told to two blocks and each sum runs once over a block:
    the work is that of a sort, whatever the range holds, and nothing is added that is not in the range.
    Rows without a time see each other.  Values are added as 1024ths and the rest, so sums of moderate
    values are rounded once, in whatever order they are added.
    """
    length = seconds + 1
    own = df.withColumn("_t", time).withColumn("_b", F.floor(F.col("_t") / length)).withColumn("_p", F.col("_t") - F.col("_b") * length)
    row = F.struct(*df.columns)
    here = own.select(F.col(by).alias("_by"), "_b", "_p", F.lit(0).alias("_old"), F.col(value).alias("_v"), row.alias("_row"))
    old = own.filter("_t IS NOT NULL").select(F.col(by).alias("_by"), (F.col("_b") + 1).alias("_b"), "_p", F.lit(1).alias("_old"), F.col(value).alias("_v"), F.lit(None).cast(own.select(row).schema[0].dataType).alias("_row"))
    block = Window.partitionBy("_by", "_b")
    start = block.orderBy("_p").rangeBetween(Window.unboundedPreceding, 0)
    # at one place the block's own rows come first: of the block before they see only what is later
    end = block.orderBy(F.desc("_p"), "_old").rowsBetween(Window.unboundedPreceding, 0)
    mine, before = F.col("_old") == 0, F.col("_old") == 1
    coarse = F.rint(F.col("_v") * 1024) / 1024
    fine = F.when(F.abs("_v") < 1e300, F.col("_v") - coarse).otherwise(0.0)
    coarse = F.when(F.abs("_v") < 1e300, coarse).otherwise(F.col("_v"))
    count = lambda c: lambda w, side: F.count(F.when(side, c)).over(w)
    total = lambda c: lambda w, side: F.coalesce(F.sum(F.when(side, c)).over(w), F.lit(0.0))
    sums = {"_n": count(F.lit(1)), "_values": count(F.col("_v")), "_coarse": total(coarse), "_fine": total(fine)}
    both = here.unionByName(old).select("*", *[f(start, mine).alias(f"{k}_a") for k, f in sums.items()], *[f(end, before).alias(f"{k}_z") for k, f in sums.items()])
    seen = {k: F.col(f"{k}_a") + F.col(f"{k}_z") for k in sums}
    return both.filter("_old = 0").select("_row.*", seen["_n"].alias("_n"), seen["_values"].alias("_values"), (seen["_coarse"] + seen["_fine"]).alias("_sum"))


def range_join(values: DataFrame, column: str, ranges: DataFrame, low: str, high: str) -> DataFrame:
    """Each value with the range [low, high) it is in; ``ranges`` is a small table, broadcast
    after its size is checked."""
    n = ranges.limit(100_001).count()
    table = F.broadcast(ranges) if n <= 100_000 else ranges
    return values.join(table, (F.col(column) >= F.col(low)) & (F.col(column) < F.col(high)))


def hash_features(df: DataFrame, key: str, text: str, slots: int) -> DataFrame:
    """(key, slot, share) of hashed words: long form, by engine functions only."""
    words = df.select(key, F.explode(F.filter(F.split(F.lower(text), r"[^a-zà-öø-ÿ]+"), lambda w: w != "")).alias("w"))
    slot = F.pmod(F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(slots)).cast("int")
    return words.groupBy(key, slot.alias("slot")).agg(F.count(F.lit(1)).alias("n"))
