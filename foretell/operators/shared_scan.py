"""Shared-scan training: one pass over packed blocks advances a whole batch of models.

In a task each block is read once: margins of all models by one matrix product, residuals by
family, and the transposed product added to the task's partial gradient.  Validation blocks only
count errors.  Partial gradients are cut into feature ranges and added up by range in the cluster
when they are large; the driver gets d x k numbers and never a row.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.blas import single_thread
from ..plans.blocks import matrix
from .random_features import Projection
from .tree_sum import SCHEMA, batch as rows_of, gather, pieces, tree_sum

#: Bytes of all partial gradients from which they are added up in the cluster first.
REDUCE_BYTES = 64 << 20
#: Doubles of one feature range.
RANGE = 1 << 16


@dataclass
class Column:
    """One model of a batch (one weight column, or one per class)."""

    model_id: int
    family: str
    rate: float
    l2: float
    projection: Projection | None = None
    weights: np.ndarray | None = None
    iterations: int = 0
    memory: dict = field(default_factory=dict)


def residuals(family: str, z: np.ndarray, y: np.ndarray) -> np.ndarray:
    """z: (n, classes) margins; y: labels.  Loss derivatives by the margin."""
    classes = z.shape[1]
    t = y[:, None] if classes == 1 else (y[:, None] == np.arange(classes)[None, :]).astype(float)
    if family == "ridge":
        return z - t
    if family == "svm":
        s = 2 * t - 1
        return np.where(s * z < 1, -s, 0.0)
    return 1.0 / (1.0 + np.exp(-np.clip(z, -500, 500))) - t


def losses(family: str, z: np.ndarray, y: np.ndarray) -> float:
    classes = z.shape[1]
    t = y[:, None] if classes == 1 else (y[:, None] == np.arange(classes)[None, :]).astype(float)
    if family == "ridge":
        return float(0.5 * ((z - t) ** 2).sum())
    s = 2 * t - 1
    return float(np.maximum(0.0, 1 - s * z).sum()) if family == "svm" else float(np.logaddexp(0, -s * z).sum())


def mistakes(family: str, z: np.ndarray, y: np.ndarray) -> float:
    """Wrong classes, or squared error of a regression."""
    if family == "ridge":
        return float(((z[:, 0] - y) ** 2).sum())
    guess = (z[:, 0] > 0).astype(int) if z.shape[1] == 1 else z.argmax(axis=1)
    return float((guess != y).sum())


def with_bias(x: np.ndarray) -> np.ndarray:
    return np.hstack((np.ones((len(x), 1)), x))


class Task:
    """What one task adds up: gradient columns, losses and counts of training and other splits."""

    def __init__(self, columns: Sequence[Column], classes: int, kernel: str):
        self.columns, self.classes, self.kernel = columns, classes, kernel
        self.groups: dict[Projection | None, list[int]] = {}
        for k, c in enumerate(columns):
            self.groups.setdefault(c.projection, []).append(k)
        self.maps = {p: p.matrix() for p in self.groups if p is not None}
        self.grads = [np.zeros_like(c.weights) for c in columns]
        self.loss = np.zeros(len(columns))
        self.rows: dict[str, int] = {}
        self.wrong: dict[str, np.ndarray] = {}

    def add(self, split: str, x: np.ndarray, y: np.ndarray) -> None:
        self.rows[split] = self.rows.get(split, 0) + len(y)
        wrong = self.wrong.setdefault(split, np.zeros(len(self.columns)))
        for p, own in self.groups.items():
            z = with_bias(x if p is None else p.apply(x, *self.maps[p]))
            if self.kernel == "rowloop":
                for k in own:  # one model after the other: a matrix-vector product each
                    self._one(split, wrong, k, z, y, np.stack([z @ w for w in self.columns[k].weights.T], axis=1))
                continue
            margins = z @ np.hstack([self.columns[k].weights for k in own])
            parts = []
            for i, k in enumerate(own):
                m = margins[:, i * self.classes : (i + 1) * self.classes]
                wrong[k] += mistakes(self.columns[k].family, m, y)
                if split == "train":
                    self.loss[k] += losses(self.columns[k].family, m, y)
                    parts.append(residuals(self.columns[k].family, m, y))
            if split == "train":
                g = z.T @ np.hstack(parts)
                for i, k in enumerate(own):
                    self.grads[k] += g[:, i * self.classes : (i + 1) * self.classes]

    def _one(self, split: str, wrong: np.ndarray, k: int, z: np.ndarray, y: np.ndarray, m: np.ndarray) -> None:
        c = self.columns[k]
        wrong[k] += mistakes(c.family, m, y)
        if split == "train":
            self.loss[k] += losses(c.family, m, y)
            r = residuals(c.family, m, y)
            self.grads[k] += np.stack([z.T @ r[:, j] for j in range(r.shape[1])], axis=1)


@dataclass
class Pass:
    """Sums over all blocks of one pass."""

    grads: list[np.ndarray]
    loss: np.ndarray
    rows: dict[str, int]
    wrong: dict[str, np.ndarray]

    def error(self, k: int, split: str = "valid") -> float:
        n = self.rows.get(split, 0)
        return float(self.wrong[split][k] / n) if n else float("nan")


def scan(blocks: DataFrame, columns: Sequence[Column], classes: int = 1, *, kernel: str = "gemm", tasks: int | None = None) -> Pass:
    """One pass over ``blocks`` with the weights of all ``columns``.

    ``tasks``: partitions of ``blocks``, where the caller knows them.  Partial sums go to the driver
    while they are small; from ``REDUCE_BYTES`` on they are added up in the cluster, by ranges of
    features and in levels of at most ``tree_sum.FAN_IN`` parts."""
    spark = blocks.sparkSession
    shared = spark.sparkContext.broadcast(list(columns))
    shapes = [c.weights.shape for c in columns]
    total = sum(int(np.prod(s)) for s in shapes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        single_thread()
        task = Task(shared.value, classes, kernel)
        for batch in batches:
            splits = batch.column("split").to_pylist()
            for i in range(batch.num_rows):
                task.add(splits[i], *matrix(batch, i))
        if not task.rows:
            return
        out = pieces("grad", np.concatenate([g.ravel() for g in task.grads]), RANGE) + pieces("loss", task.loss, RANGE)
        for s, n in task.rows.items():
            out += pieces(f"rows/{s}", np.asarray([float(n)]), RANGE) + pieces(f"wrong/{s}", task.wrong[s], RANGE)
        yield rows_of(TaskContext.get().partitionId(), out)

    out = blocks.select("split", "n", "x", "y").mapInArrow(run, SCHEMA)
    tasks = blocks.rdd.getNumPartitions() if tasks is None else tasks
    if 8 * total * max(1, tasks) > REDUCE_BYTES:
        out = tree_sum(out, tasks)
    got = gather(out.select("kind", "part", "payload").collect(), RANGE)
    shared.destroy()
    flat, grads, at = got.get("grad", np.zeros(total)), [], 0
    for s in shapes:
        n = int(np.prod(s))
        grads.append(flat[at : at + n].reshape(s))
        at += n
    named = lambda kind: {k[len(kind) :]: v for k, v in got.items() if k.startswith(kind)}
    return Pass(grads, got.get("loss", np.zeros(len(columns))), {k: int(v[0]) for k, v in named("rows/").items()}, named("wrong/"))


def update(c: Column, grad: np.ndarray, rows: int, *, step: str = "plain", scale: str = "mean") -> None:
    """One step of one model; the bias is not regularised.

    ``step``: plain, nesterov (momentum 0.9) or adagrad (per-coordinate rates)."""
    g = grad / rows if scale == "mean" else grad.copy()
    g[1:] += c.l2 * c.weights[1:]
    if step == "adagrad":
        c.memory["sum"] = c.memory.get("sum", 1e-8) + g * g
        c.weights = c.weights - c.rate * g / np.sqrt(c.memory["sum"])
    elif step == "nesterov":
        v = 0.9 * c.memory.get("v", 0.0) - c.rate * g
        c.weights = c.weights + 0.9 * v - c.rate * g
        c.memory["v"] = v
    else:
        c.weights = c.weights - c.rate * g
    c.iterations += 1


def start(c: Column, d: int, classes: int = 1) -> Column:
    """Zero weights of the right shape."""
    size = (c.projection.size if c.projection else d) + 1
    c.weights = np.zeros((size, classes))
    return c


def train(blocks: DataFrame, columns: Sequence[Column], iterations: int, *, classes: int = 1, kernel: str = "gemm", step: str = "plain", minibatches: int = 1) -> Pass:
    """``iterations`` scans of a batch.  With ``minibatches`` each scan is dealt in that many
    updates over contiguous blocks."""
    tasks = blocks.rdd.getNumPartitions()
    for _ in range(iterations):
        for m in range(minibatches):
            own = blocks if minibatches == 1 else blocks.filter(F.pmod("block_id", F.lit(minibatches)) == m)
            p = scan(own, columns, classes, kernel=kernel, tasks=tasks)
            if p.rows.get("train"):
                for k, c in enumerate(columns):
                    update(c, p.grads[k], p.rows["train"], step=step)
    return scan(blocks, columns, classes, kernel=kernel, tasks=tasks)
