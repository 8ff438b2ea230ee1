"""Reading the given tables, other formats, and writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Temporary views of the given tables (all by default)."""
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """parquet, orc, csv, json, text, or any registered data source."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", *, partition_by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    writer = df.write.format(kind).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder of any file system that Spark can reach; the session may be gone already."""
    try:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    except Exception:  # noqa: BLE001  at the end of the program there is no JVM to ask
        pass


def drain(df: DataFrame) -> None:
    """Run a plan without keeping its rows (for timing)."""
    df.write.format("noop").mode("overwrite").save()


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share (spark.checkpoint.dir).

    Only a session on one machine may leave it unset; there a local folder is used."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        import tempfile

        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        where = f"file://{tempfile.mkdtemp(prefix='foretell-')}"
        spark.conf.set("spark.checkpoint.dir", where)
    return where.rstrip("/")
