"""Sums of partial arrays in levels, so that no group gathers more than a few parts."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Partial arrays that one group adds up.
FAN_IN = 64
SCHEMA = "kind string, part bigint, task bigint, payload binary"


def tree_sum(parts: DataFrame, tasks: int, *, fan_in: int = FAN_IN) -> DataFrame:
    """(kind, part, task, payload) to (kind, part, payload): payloads of doubles added by kind and part.

    ``tasks``: number of values of ``task`` (0 .. tasks - 1), at most one row each for a kind and
    part.  Every level divides it by ``fan_in``; a group never has more rows than that."""

    def add_up(group: pa.Table) -> pa.Table:
        total = np.sum([np.frombuffer(p.as_buffer(), np.float64) for p in group.column("payload")], axis=0)
        first = group.slice(0, 1)
        task = pa.array([first.column("task")[0].as_py() // fan_in], pa.int64())
        return pa.table({"kind": first.column("kind"), "part": first.column("part"), "task": task, "payload": pa.array([total.tobytes()], pa.binary())})

    while True:
        parts = parts.groupBy("kind", "part", F.floor(F.col("task") / fan_in)).applyInArrow(add_up, SCHEMA)
        tasks = -(-tasks // fan_in)
        if tasks <= 1:
            return parts.drop("task")


def pieces(kind: str, values: np.ndarray, size: int) -> list[tuple[str, int, bytes]]:
    """An array as rows of at most ``size`` doubles."""
    flat = np.ascontiguousarray(values, np.float64).ravel()
    return [(kind, a // size, flat[a : a + size].tobytes()) for a in range(0, max(1, len(flat)), size)]


def batch(task: int, rows: list[tuple[str, int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows], pa.int64()), pa.array([task] * len(rows), pa.int64()), pa.array([r[2] for r in rows], pa.binary())], ["kind", "part", "task", "payload"])


def gather(rows: list, size: int) -> dict[str, np.ndarray]:
    """The arrays of collected rows (kind, part, payload), partial ones added in a fixed order."""
    parts: dict[str, dict[int, np.ndarray]] = {}
    for kind, part, payload in sorted(((r["kind"], r["part"], bytes(r["payload"])) for r in rows)):
        own, v = parts.setdefault(kind, {}), np.frombuffer(payload, np.float64)
        own[part] = own[part] + v if part in own else v
    return {kind: np.concatenate([own[k] for k in sorted(own)]) for kind, own in parts.items()}
