"""Learning tasks on the given tables: key, label and predictors, in Spark and in ANSI SQL.

Real signal is in documents and their labels; other targets are planted; ``embeddings.label``,
return flags and event types are negative controls that nothing can be learnt from.  Documents
are keyed by a digest of their text, so copies never stand on both sides of a split.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import draws
from ..sources.tables import table

TRAIN, VALID = 0.7, 0.9

_LINE_KEY = "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(l_quantity AS BIGINT), CAST(round(l_extendedprice * 100) AS BIGINT))"
_LINE = ("(l_quantity - 25.5) / 14.4", "(l_extendedprice - 53000) / 30000", "(l_discount - 0.05) / 0.029", "(l_tax - 0.04) / 0.0235", "(l_linenumber - 4) / 2.0")
_TEXT = (
    "ln(1 + length(text)) - 7",
    "10.0 * (length(text) - length(translate(text, '#$%&*|<>', ''))) / (1 + length(text))",
    "10.0 * (length(text) - length(translate(text, '0123456789', ''))) / (1 + length(text))",
)
_DISTINCT_SPARK = "size(array_distinct(split(text, ' '))) / CAST(size(split(text, ' ')) AS DOUBLE)"
_DISTINCT_SQL = "len(list_distinct(string_split(text, ' '))) / CAST(len(string_split(text, ' ')) AS DOUBLE)"


@dataclass(frozen=True)
class Task:
    """``features`` are SQL expressions that Spark and DuckDB read alike, unless ``sql_features``
    gives the DuckDB text.  ``source`` is the FROM item."""

    name: str
    tables: tuple[str, ...]
    source: str
    key: str
    label: str
    features: tuple[str, ...]
    sql_features: tuple[str, ...] | None = None
    classes: int = 2
    regression: bool = False
    sql_key: str | None = None

    def names(self) -> list[str]:
        return [f"x{i + 1}" for i in range(len(self.features))]


TASKS: dict[str, Task] = {}


def _add(task: Task) -> Task:
    TASKS[task.name] = task
    return task


DOC_QUALITY = _add(Task("doc_quality", ("documents", "labels"), "documents JOIN labels USING (doc_id)", "md5(text)", "quality", (*_TEXT, _DISTINCT_SPARK), (*_TEXT, _DISTINCT_SQL)))
DOC_ENGLISH = _add(Task("doc_english", ("documents",), "documents", "md5(text)", "CASE WHEN lang = 'en' THEN 1 ELSE 0 END", tuple(f"10.0 * (length(text) - length(replace(text, '{s}', ''))) / (1 + length(text))" for s in (" the ", " de ", " der ", " und ", " la ", " en ", "th", "que"))))
LINE_LINEAR = _add(Task("line_linear", ("lineitem",), "lineitem", _LINE_KEY, "CASE WHEN 1000 * l_quantity + 0.5 * l_extendedprice - 200000 * l_discount > 42000 THEN 1 ELSE 0 END", _LINE))
LINE_XOR = _add(Task("line_xor", ("lineitem",), "lineitem", _LINE_KEY, "CASE WHEN (l_quantity - 25.5) * (l_extendedprice - 53000) > 0 THEN 1 ELSE 0 END", _LINE))
EMB_PLANE = _add(Task("emb_plane", ("embeddings",), "embeddings", "vec_id", "CASE WHEN " + " + ".join(f"CAST(embedding[{{{i}}}] AS DOUBLE)" for i in range(8)) + " > 0 THEN 1 ELSE 0 END", tuple(f"8 * CAST(embedding[{{{i}}}] AS DOUBLE)" for i in range(64))))
LINE_SKEW = _add(Task("line_skew", ("lineitem",), "lineitem", _LINE_KEY, "CASE WHEN 1000 * l_quantity + 0.5 * l_extendedprice - 200000 * l_discount > 62000 THEN 1 ELSE 0 END", _LINE))
LINE_147 = _add(Task("line_147", ("lineitem",), "lineitem", _LINE_KEY, "(l_linenumber - 1) * 21 + CAST(least(20, floor(l_extendedprice / 5000)) AS INT)", _LINE, classes=147))
DOC_LANG4 = _add(Task("doc_lang4", ("documents",), "documents", "md5(text)", "CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END", DOC_ENGLISH.features, classes=4))
LINE_REVENUE = _add(Task("line_revenue", ("lineitem",), "lineitem", _LINE_KEY, "l_extendedprice * (1 - l_discount) * (1 + l_tax) / 50000", _LINE[:4], regression=True))
CONTROL_RETURN = _add(Task("control_return", ("lineitem",), "lineitem", _LINE_KEY, "CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END", _LINE))
CONTROL_STATUS = _add(Task("control_status", ("lineitem",), "lineitem", _LINE_KEY, "CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END", _LINE))
CONTROL_EMB = _add(Task("control_embedding", ("embeddings",), "embeddings", "vec_id", "CASE WHEN label = 0 THEN 1 ELSE 0 END", tuple(f"8 * CAST(embedding[{{{i}}}] AS DOUBLE)" for i in range(8))))
CONTROL_EVENT = _add(Task("control_event", ("events",), "events", "event_id", "CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END", ("(value - 50) / 50.0", "(user_id % 100) / 100.0")))
CONTROL_ORDER = _add(Task("control_order", ("orders",), "orders", "o_orderkey", "CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END", ("(o_totalprice - 150000) / 100000.0", "(o_custkey % 100) / 100.0")))
DOC_TOXIC = _add(Task("doc_toxic", ("documents", "labels"), "documents JOIN labels USING (doc_id)", "md5(text)", "toxic", tuple(f"CASE WHEN lower(text) LIKE '%{w}%' THEN 1.0 ELSE 0.0 END" for w in ("idiot", "trash", "loser", "moron", "stupid", "pathetic", "scum", "clown"))))


def _indexed(text: str, first: int) -> str:
    """Array positions {i} in an engine whose arrays start at ``first``."""
    out, at = [], 0
    while (i := text.find("[{", at)) >= 0:
        j = text.index("}]", i)
        out += [text[at:i], f"[{int(text[i + 2 : j]) + first}]"]
        at = j + 2
    return "".join([*out, text[at:]])


def split_of(key: Column, seed: int = 0) -> Column:
    """train, valid or test (70/20/10) by a draw on the key."""
    u = draws.uniform(f"split:{seed}", key)
    return F.when(u < TRAIN, "train").when(u < VALID, "valid").otherwise("test")


def split_sql(key: str, seed: int = 0) -> str:
    u = draws.uniform_sql(f"split:{seed}", key)
    return f"CASE WHEN {u} < {TRAIN} THEN 'train' WHEN {u} < {VALID} THEN 'valid' ELSE 'test' END"


def downsample(df: DataFrame, key: str | Column, share: float, seed: int = 0) -> DataFrame:
    """A deterministic share of the rows, as a filter that can run before any expansion."""
    key = F.col(key) if isinstance(key, str) else key
    return df.filter(draws.uniform(f"sample:{seed}", key) < share)


def load(spark: SparkSession, sf_dir: str, task: Task, *, seed: int = 0, noise: float = 0.0, wide: bool = False) -> DataFrame:
    """key, split, label, and ``features`` (array) or x1..xd (``wide``).

    ``noise``: share of binary labels flipped, by a draw on the key."""
    frames = [table(spark, sf_dir, t) for t in task.tables]
    base = frames[0]
    for other in frames[1:]:
        base = base.join(other, "doc_id")
    label = F.expr(_indexed(task.label, 0)).cast("double" if task.regression else "int")
    out = base.select(F.expr(task.key).cast("string").alias("key"), label.alias("label"), *[F.expr(_indexed(f, 0)).cast("double").alias(n) for f, n in zip(task.features, task.names(), strict=True)])
    if noise:
        out = out.withColumn("label", F.when(draws.uniform(f"noise:{seed}", F.col("key")) < noise, 1 - F.col("label")).otherwise(F.col("label")))
    out = out.withColumn("split", split_of(F.col("key"), seed))
    return out.select("key", "split", "label", *task.names()) if wide else out.select("key", "split", "label", F.array(*task.names()).alias("features"))


def task_sql(task: Task, *, seed: int = 0, noise: float = 0.0) -> str:
    """DuckDB SELECT of key, split, label, x1..xd."""
    label = _indexed(task.label, 1)
    features = ", ".join(f"CAST({_indexed(f, 1)} AS DOUBLE) AS {n}" for f, n in zip(task.sql_features or task.features, task.names(), strict=True))
    y = f"CASE WHEN {draws.uniform_sql(f'noise:{seed}', 'key')} < {noise} THEN 1 - label ELSE label END" if noise else "label"
    return f"SELECT key, {split_sql('key', seed)} AS split, {y} AS label, {', '.join(task.names())} FROM (SELECT CAST({task.key} AS VARCHAR) AS key, {label} AS label, {features} FROM {task.source}) AS raw"


@dataclass
class FeatureSpec:
    """Means and deviations of the training split, with an indicator for missing values."""

    names: list[str]
    mean: list[float] = field(default_factory=list)
    scale: list[float] = field(default_factory=list)
    missing: list[bool] = field(default_factory=list)

    @classmethod
    def fit(cls, df: DataFrame, names: list[str]) -> FeatureSpec:
        stats = df.agg(*[e for n in names for e in (F.avg(n).alias(f"{n}_m"), F.stddev_pop(n).alias(f"{n}_s"), F.count_if(F.col(n).isNull()).alias(f"{n}_0"))]).first()
        spec = cls(list(names))
        for n in names:
            spec.mean.append(float(stats[f"{n}_m"] or 0.0))
            spec.scale.append(float(stats[f"{n}_s"] or 0.0) or 1.0)
            spec.missing.append(bool(stats[f"{n}_0"]))
        return spec

    def columns(self) -> list[Column]:
        out = []
        for n, m, s, gap in zip(self.names, self.mean, self.scale, self.missing, strict=True):
            out.append((F.coalesce(F.col(n).cast("double"), F.lit(m)) - F.lit(m)) / F.lit(s))
            if gap:
                out.append(F.col(n).isNull().cast("double"))
        return out

    def transform(self, df: DataFrame, *keep: str) -> DataFrame:
        return df.select(*keep, F.array(*self.columns()).alias("features"))


_NUMERIC = ("tinyint", "smallint", "int", "bigint", "float", "double", "boolean")


#: Slots of a text's hashed words, and what a word's share of the text is multiplied by.
SLOTS, WORD_SCALE = 256, 16.0


def word_slots(text: str, slots: int = SLOTS) -> str:
    """SQL expression: the hashed slot of every word of ``text``, as array<int>; empty without words."""
    return f"transform(filter(split(lower({text}), '[^\\\\p{{L}}\\\\p{{N}}#$%&*|<>]+'), w -> w <> ''), w -> CAST(pmod(xxhash64(w), {slots}) AS INT))"


def hashed_features(df: DataFrame, keep: list[str], numbers: str, texts: list[str], slots: int = SLOTS) -> DataFrame:
    """``keep`` and ``features``: the array ``numbers`` followed by, for every array of word slots in
    ``texts``, the share of the words in each slot times ``WORD_SCALE``."""
    kept = df.select(*keep).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            parts = [np.asarray(batch.column(numbers).flatten(), np.float64).reshape(n, -1)]
            for t in texts:
                column = batch.column(t)
                sizes = np.asarray(pc.fill_null(pc.list_value_length(column), 0), np.int64)
                place = np.repeat(np.arange(n), sizes) * slots + np.asarray(column.flatten(), np.int64)
                counts = np.bincount(place, minlength=n * slots).reshape(n, slots)
                parts.append(WORD_SCALE * counts / np.maximum(1, sizes)[:, None])
            x = np.hstack(parts)
            features = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1]), pa.int32()), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), features], [*keep, "features"])

    schema = T.StructType([*kept.fields, T.StructField("features", T.ArrayType(T.DoubleType()))])
    return df.select(*keep, numbers, *texts).mapInArrow(run, schema)


def load_hashed(spark: SparkSession, sf_dir: str, task: Task, *, slots: int = SLOTS, numbers: bool = True, seed: int = 0) -> DataFrame:
    """key, split, label, features of a task on texts: its own features (unless ``numbers`` is false)
    and the hashed words of ``text``."""
    base = table(spark, sf_dir, task.tables[0])
    for other in task.tables[1:]:
        base = base.join(table(spark, sf_dir, other), "doc_id")
    own = F.array(*[F.expr(f).cast("double") for f in task.features]) if numbers else F.array().cast("array<double>")
    rows = base.select(F.expr(task.key).cast("string").alias("key"), F.expr(task.label).cast("int").alias("label"), own.alias("_numbers"), F.expr(word_slots("coalesce(text, '')", slots)).alias("_slots"))
    rows = rows.withColumn("split", split_of(F.col("key"), seed))
    return hashed_features(rows, ["key", "split", "label"], "_numbers", ["_slots"], slots)


def text_predictors(df: DataFrame, names: list[str]) -> list[str]:
    """Those of ``names`` that are strings: their words are hashed, whatever their number of levels."""
    kinds = dict(df.dtypes)
    return [n for n in names if kinds[n] == "string"]


def numeric_expressions(df: DataFrame, names: list[str]) -> list[tuple[str, str]]:
    """Predictor columns of any supported type as named SQL expressions of type double.

    Numbers, booleans and decimals are cast; timestamps and dates give day, hour and weekday;
    arrays of numbers are expanded to the length of the longest; strings give statistics of the
    text (their words are hashed besides, see ``text_predictors``); binary and nested types raise.
    """
    out: list[tuple[str, str]] = []
    kinds = dict(df.dtypes)
    for n in names:
        kind, q = kinds[n], f"`{n}`"
        if kind in _NUMERIC or kind.startswith("decimal"):
            out.append((n, f"CAST({q} AS DOUBLE)"))
        elif kind in ("timestamp", "timestamp_ntz", "date"):
            out += [(f"{n}_day", f"CAST(datediff({q}, DATE'1998-06-01') AS DOUBLE)"), (f"{n}_weekday", f"CAST(dayofweek({q}) AS DOUBLE)")]
            if kind != "date":
                out.append((f"{n}_hour", f"CAST(hour({q}) AS DOUBLE)"))
        elif kind in ("array<float>", "array<double>", "array<int>"):
            longest = df.agg(F.max(F.size(n)).alias("n")).first()["n"] or 0
            out += [(f"{n}_{i}", f"CAST(get({q}, {i}) AS DOUBLE)") for i in range(max(0, longest))]
        elif kind == "string":
            size = f"(length({q}) + 1)"
            out += [
                (f"{n}_length", f"ln(CAST({size} AS DOUBLE))"),
                (f"{n}_marks", f"10.0D * (length({q}) - length(translate({q}, '#$%&*|<>', ''))) / {size}"),
                (f"{n}_digits", f"10.0D * (length({q}) - length(translate({q}, '0123456789', ''))) / {size}"),
                (f"{n}_distinct", f"size(array_distinct(split({q}, ' '))) / CAST(size(split({q}, ' ')) AS DOUBLE)"),
            ]
        else:
            raise TypeError(f"column {n} of type {kind} is no predictor")
    return out
