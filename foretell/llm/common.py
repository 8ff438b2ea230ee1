"""Small helpers shared by the training-data operators: reading, materialising, skew-safe joins."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A key is hot when it holds at least this share of the rows, so there are at most 1 / share hot keys.
HOT_SHARE = 1 / 512

_made: dict[str, SparkSession] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir of the session.

    Only where it is unset (tests on one machine) a folder of the driver's own is used.
    """
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        import tempfile

        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        where = f"file://{tempfile.mkdtemp(prefix='foretell-')}"
        spark.conf.set("spark.checkpoint.dir", where)
    return where.rstrip("/")


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: lineage is cut there,
    so a lost executor costs no more than the stage that was running."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/foretell-{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if not _made:
        atexit.register(_remove_all)
    _made[path] = spark
    return spark.read.schema(df.schema).parquet(path)


def _remove_all() -> None:
    for path in list(_made):
        release_path(path)


def release_path(path: str) -> None:
    spark = _made.pop(path, None)
    try:
        jvm = spark._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    except Exception:  # noqa: BLE001  the session may be gone at interpreter exit; the folder has its own expiry
        pass


def release(*frames: DataFrame) -> None:
    """Delete materialised frames that nothing reads any more."""
    for df in frames:
        files = set(df.inputFiles())
        for path in list(_made):
            if any(f"/{path.rsplit('/', 1)[-1]}/" in f for f in files):
                release_path(path)


def salted_join(left: DataFrame, right: DataFrame, keys: Sequence[str], rows: str, total: int, how: str = "inner") -> DataFrame:
    """Join ``left`` to ``right``, which has one row per key and in column ``rows`` the number of
    left rows of that key.  Keys that hold HOT_SHARE of ``total`` or more (a proven bound of
    1 / HOT_SHARE keys) are dealt over several partitions by a salt on either side; the other
    keys join as usual."""
    least = max(1000, int(total * HOT_SHARE))
    parts = 64
    hot = F.broadcast(right.filter(F.col(rows) >= least).select(*keys).withColumn("_hot", F.lit(True)))
    left = left.join(hot, list(keys), "left").withColumn("_salt", F.when(F.col("_hot"), (F.rand(7) * parts).cast("int")).otherwise(F.lit(0))).drop("_hot")
    right = right.withColumn("_salt", F.explode(F.when(F.col(rows) >= least, F.sequence(F.lit(0), F.lit(parts - 1))).otherwise(F.array(F.lit(0)))))
    return left.join(right, [*keys, "_salt"], how).drop("_salt")


def empty(spark: SparkSession, schema: str) -> DataFrame:
    return spark.createDataFrame([], T._parse_datatype_string(schema))


def pick(values: Sequence[float], index: Column) -> Column:
    """values[index] for a short driver-side list."""
    return F.element_at(F.array(*[F.lit(v) for v in values]), index.cast("int") + 1)
