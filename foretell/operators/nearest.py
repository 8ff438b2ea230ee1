"""Exact nearest neighbours of stated query rows against all rows, in blocks of queries."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.blas import single_thread

#: Query rows that are broadcast together, and lists of one query merged in one group.
BLOCK, FAN_IN = 4096, 64


def nearest(rows: DataFrame, queries: DataFrame, k: int, *, id_col: str = "vec_id", vector_col: str = "embedding", digits: int = 9) -> DataFrame:
    """probe, vec_id, rn (1 .. k): the ``k`` rows of largest dot product (rounded to ``digits``, then of
    least id) with every row of ``queries``, itself left out.

    A task compares its rows with a block of queries by matrix products and keeps ``k`` a query;
    the lists are merged in levels, so no group has more than ``FAN_IN`` lists."""
    queries = queries.select(F.col(id_col).alias("id"), F.col(vector_col).alias("v")).dropna()
    count = -(-queries.count() // BLOCK)
    spark, found = rows.sparkSession, None
    rows = rows.select(F.col(id_col).alias("id"), F.col(vector_col).alias("v")).dropna()
    for b in range(count):
        own = queries if count == 1 else queries.filter(F.pmod(F.xxhash64("id"), F.lit(count)) == b)
        probes = own.collect()
        if not probes:
            continue
        shared = spark.sparkContext.broadcast((np.asarray([p["id"] for p in probes]), np.asarray([p["v"] for p in probes], np.float64)))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            single_thread()
            ids, vectors = shared.value
            best_id, best = np.empty((len(ids), 0), np.int64), np.empty((len(ids), 0))
            for batch in batches:
                if not batch.num_rows:
                    continue
                own = batch.column("id").to_numpy(zero_copy_only=False)
                x = batch.column("v").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(own), -1)
                for at in range(0, len(own), 1024):
                    dots = np.round(vectors @ x[at : at + 1024].T, digits)
                    dots[ids[:, None] == own[None, at : at + 1024]] = -np.inf
                    value = np.hstack((best, dots))
                    name = np.hstack((best_id, np.broadcast_to(own[at : at + 1024], dots.shape)))
                    order = np.lexsort((name, -value), axis=1)[:, :k]
                    best, best_id = np.take_along_axis(value, order, 1), np.take_along_axis(name, order, 1)
            probe, some = np.repeat(ids, best.shape[1]), np.isfinite(best).ravel()
            task = np.full(some.sum(), TaskContext.get().partitionId())
            yield pa.RecordBatch.from_arrays([pa.array(probe[some]), pa.array(best_id.ravel()[some]), pa.array(best.ravel()[some]), pa.array(task, pa.int64())], ["probe", "id", "dot", "task"])

        part = rows.mapInArrow(run, "probe long, id long, dot double, task long")
        found = part if found is None else found.unionByName(part)
    if found is None:
        return spark.createDataFrame([], f"probe long, {id_col} long, rn int")
    tasks = rows.rdd.getNumPartitions()
    while True:
        lists = found.groupBy("probe", F.floor(F.col("task") / FAN_IN).alias("task")).agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("dot")).alias("d"), "id"))), 1, k).alias("l"))
        tasks = -(-tasks // FAN_IN)
        if tasks <= 1:
            return lists.select("probe", F.posexplode("l").alias("pos", "b")).select("probe", F.col("b.id").alias(id_col), (F.col("pos") + 1).alias("rn"))
        found = lists.select("probe", "task", F.explode("l").alias("b")).select("probe", F.col("b.id").alias("id"), (-F.col("b.d")).alias("dot"), "task")
