"""Packed feature blocks: many rows in one binary, row-major value, ready for matrix products."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import delete, shared_dir

#: Bytes of one block aimed at.
BLOCK_BYTES = 2 << 20
SCHEMA = "split string, block_id bigint, n int, x binary, y array<double>"
_ARROW = pa.schema([("split", pa.string()), ("block_id", pa.int64()), ("n", pa.int32()), ("x", pa.binary()), ("y", pa.list_(pa.float64()))])


def pack(df: DataFrame, *, rows_per_block: int | None = None) -> DataFrame:
    """(split, label, features) to blocks; rows stay in their partition, so nothing is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, made = (TaskContext.get().partitionId() if TaskContext.get() else 0) << 32, 0
        held: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}

        def block(split: str) -> pa.RecordBatch:
            nonlocal made
            x = np.concatenate([p[0] for p in held[split]])
            y = np.concatenate([p[1] for p in held[split]])
            held[split] = []
            made += 1
            return pa.RecordBatch.from_arrays([pa.array([split]), pa.array([base + made], pa.int64()), pa.array([len(y)], pa.int32()), pa.array([x.tobytes()], pa.binary()), pa.array([y.tolist()], pa.list_(pa.float64()))], schema=_ARROW)

        for batch in batches:
            if not batch.num_rows:
                continue
            features = batch.column("features")
            x = features.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(batch.num_rows, -1)
            y = batch.column("label").cast(pa.float64()).to_numpy(zero_copy_only=False)
            splits = np.asarray(batch.column("split").to_pylist())
            most = rows_per_block or max(64, BLOCK_BYTES // (8 * max(1, x.shape[1])))
            for split in np.unique(splits):
                own = splits == split
                for at in range(0, int(own.sum()), most):
                    held.setdefault(split, []).append((x[own][at : at + most], y[own][at : at + most]))
                    if sum(len(p[1]) for p in held[split]) >= most:
                        yield block(split)
        for split in [s for s, parts in held.items() if parts]:
            yield block(split)

    return df.select("split", "label", "features").mapInArrow(run, SCHEMA)


def store(blocks: DataFrame) -> DataFrame:
    """Write blocks to the shared folder and read them back: passes read packed Parquet, not the
    relation, and a lost executor costs a re-read.  ``release`` deletes them, and so does the end of
    the program."""
    path = f"{shared_dir(blocks.sparkSession)}/foretell-blocks-{uuid.uuid4().hex}"
    # a row group a block: sizes are looked at after every row (after 100 by default), so that the blocks of
    # one file are read by several tasks
    blocks.write.option("parquet.block.size", BLOCK_BYTES).option("parquet.page.size.row.check.min", 1).option("compression", "none").parquet(path)
    if not _stored:
        atexit.register(release)
    out = blocks.sparkSession.read.schema(SCHEMA).parquet(path)
    _stored.append((path, blocks.sparkSession, out))
    return out


_stored: list[tuple[str, SparkSession, DataFrame]] = []


def release(blocks: DataFrame | None = None) -> None:
    """Delete stored blocks (all of them by default)."""
    for entry in [e for e in _stored if blocks is None or e[2] is blocks]:
        _stored.remove(entry)
        delete(entry[1], entry[0])


def matrix(batch: pa.RecordBatch, row: int) -> tuple[np.ndarray, np.ndarray]:
    """Views of one block's features and labels, without copying."""
    n = batch.column("n")[row].as_py()
    x = np.frombuffer(batch.column("x")[row].as_buffer(), np.float64).reshape(n, -1)
    y = batch.column("y")[row].values.to_numpy(zero_copy_only=False)
    return x, y
