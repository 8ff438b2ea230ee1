"""Ensembles of models that a plan has trained anyway."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame

from ..operators import shared_scan
from .blocks import matrix


def votes(blocks: DataFrame, columns: Sequence[shared_scan.Column], split: str = "valid") -> tuple[np.ndarray, np.ndarray]:
    """Counts of vote patterns of up to 16 binary models: (patterns x models) and by label.

    Patterns, not rows, reach the driver: at most 2 ** models for either label."""
    if len(columns) > 16:
        raise ValueError("at most 16 models vote together")
    shared = blocks.sparkSession.sparkContext.broadcast(list(columns))

    def run(batches):
        import pyarrow as pa

        table = np.zeros((1 << len(shared.value), 2), np.int64)
        for batch in batches:
            for i in range(batch.num_rows):
                x, y = matrix(batch, i)
                code = np.zeros(len(y), np.int64)
                for k, c in enumerate(shared.value):
                    z = shared_scan.with_bias(x if c.projection is None else c.projection.transform(x))
                    code |= (z @ c.weights[:, 0] > 0).astype(np.int64) << k
                np.add.at(table, (code, y.astype(int)), 1)
        own = np.argwhere(table)
        yield pa.RecordBatch.from_arrays([pa.array(own[:, 0]), pa.array(own[:, 1]), pa.array(table[own[:, 0], own[:, 1]])], ["pattern", "label", "n"])

    got = blocks.filter(f"split = '{split}'").select("n", "x", "y").mapInArrow(run, "pattern long, label long, n long").groupBy("pattern", "label").sum("n").collect()
    table: dict[int, list[int]] = {}
    for pattern, label, n in got:
        table.setdefault(pattern, [0, 0])[label] += n
    codes = sorted(table)
    return np.asarray([[c >> k & 1 for k in range(len(columns))] for c in codes]), np.asarray([table[c] for c in codes])


def majority_error(patterns: np.ndarray, counts: np.ndarray, members: Sequence[int]) -> float:
    says = (patterns[:, list(members)].mean(axis=1) > 0.5).astype(int)
    return float(1 - counts[np.arange(len(says)), says].sum() / counts.sum())


def greedy(patterns: np.ndarray, counts: np.ndarray, most: int = 5) -> tuple[list[int], float]:
    """Add the model that helps the vote most (with repetition) until none does."""
    members: list[int] = []
    best = float("inf")
    while len(members) < most:
        error, k = min((majority_error(patterns, counts, [*members, k]), k) for k in range(patterns.shape[1]))
        if error >= best:
            break
        best, members = error, [*members, k]
    return members, best
