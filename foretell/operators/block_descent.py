"""Nonlinear SVM by block coordinate descent over random features.

A pass takes one block of features: every task draws the block's projection again, adds up the
Gram matrix of the block and its product with what is left to explain, and the driver solves the
regularised normal equations for all classes and all ridge values that share the projection.
Several projections take one pass together.  Margins are recomputed from all weights in the same
task, so nothing of the size of the data is kept.  For the squared loss a projection that is no
wider than the widest block needs one pass only: its whole Gram matrix gives the sums of every block.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from ..functions.blas import single_thread
from ..plans.blocks import matrix
from .random_features import Projection
from .tree_sum import SCHEMA, batch as rows_of, gather, pieces, tree_sum

#: Doubles of one range of a Gram matrix.
RANGE = 1 << 16
#: Doubles of the features that are computed at a time: they stay in a core's cache.
CHUNK = 1 << 17
#: Features up to which the whole Gram matrix of a projection is kept (a block has no more).
KEPT = 512


def targets(y: np.ndarray, classes: int) -> np.ndarray:
    """+1 for a row's class and -1 for the others (one column for two classes)."""
    if classes <= 2:
        return (2 * y - 1)[:, None]
    return np.where(y[:, None] == np.arange(classes)[None, :], 1.0, -1.0)


class _Sums:
    """What one task adds up for one projection and one block of its features."""

    def __init__(self, job: tuple):
        self.projection, self.weights, self.l2s, self.classes, self.hinge, self.full, self.first, self.count = job
        self.own = self.projection.matrix(self.first, self.count) if self.count else None
        self.drawn: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        self.gram, self.rhs, self.n = np.zeros((self.count, self.count)), {v: 0.0 for v in self.l2s}, 0
        self.wrong, self.objective, self.seen = {v: np.zeros(3) for v in self.l2s}, {v: 0.0 for v in self.l2s}, np.zeros(3)

    def add(self, split: str, x: np.ndarray, y: np.ndarray) -> None:
        rows = max(64, CHUNK // max(1, self.count, min(self.full, self.projection.size), self.classes))
        for a in range(0, len(y), rows):
            self._add(split, x[a : a + rows], y[a : a + rows])

    def _add(self, split: str, x: np.ndarray, y: np.ndarray) -> None:
        margins = {v: np.zeros((len(y), self.weights[v].shape[1])) for v in self.l2s}
        for a in range(0, self.projection.size, self.full):
            if any(self.weights[v][a : a + self.full].any() for v in self.l2s):
                if a not in self.drawn:
                    self.drawn[a] = self.projection.matrix(a, min(self.full, self.projection.size - a))
                z = self.projection.apply(x, *self.drawn[a])
                for v in self.l2s:
                    margins[v] += z @ self.weights[v][a : a + self.full]
        t, place = targets(y, self.classes), ("train", "valid", "test").index(split)
        for v in self.l2s:
            guess = (margins[v][:, 0] > 0).astype(int) if t.shape[1] == 1 else margins[v].argmax(axis=1)
            self.wrong[v][place] += (guess != y).sum()
        self.seen[place] += len(y)
        if split != "train":
            return
        self.n += len(y)
        z = self.projection.apply(x, *self.own) if self.count else None
        for v in self.l2s:
            left = t - margins[v]
            if self.hinge:
                active = (t * margins[v] < 1)[:, 0]
                self.objective[v] += float((np.maximum(0.0, 1 - t * margins[v]) ** 2).sum())
                if self.count:
                    self.gram += z[active].T @ z[active]
                    self.rhs[v] = self.rhs[v] + z[active].T @ left[active]
            else:
                self.objective[v] += float((left**2).sum())
                if self.count:
                    self.rhs[v] = self.rhs[v] + z.T @ left
        if self.count and not self.hinge:
            self.gram += z.T @ z

    def rows(self, at: int) -> list[tuple[str, int, bytes]]:
        out = pieces(f"{at}/n", np.asarray([float(self.n)]), RANGE) + pieces(f"{at}/seen", self.seen, RANGE)
        if self.count:
            out += pieces(f"{at}/gram", self.gram, RANGE)
        for k, v in enumerate(self.l2s):
            if self.count:
                rhs = self.rhs[v] if np.ndim(self.rhs[v]) else np.zeros((self.count, self.weights[v].shape[1]))
                out += pieces(f"{at}/rhs/{k}", rhs, RANGE)
            out += pieces(f"{at}/wrong/{k}", self.wrong[v], RANGE) + pieces(f"{at}/objective/{k}", np.asarray([self.objective[v]]), RANGE)
        return out


def _pass(blocks: DataFrame, jobs: Sequence[tuple], tasks: int | None = None) -> list[dict[str, np.ndarray]]:
    """One pass over ``blocks`` for all jobs, its sums added in levels of bounded groups."""
    shared = blocks.sparkSession.sparkContext.broadcast(list(jobs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        single_thread()
        sums = [_Sums(job) for job in shared.value]
        for batch in batches:
            for i in range(batch.num_rows):
                x, y = matrix(batch, i)
                for s in sums:
                    s.add(batch.column("split")[i].as_py(), x, y)
        if sums and sums[0].seen.sum():
            yield rows_of(TaskContext.get().partitionId(), [r for k, s in enumerate(sums) for r in s.rows(k)])

    out = blocks.select("split", "n", "x", "y").mapInArrow(run, SCHEMA)
    got = gather(tree_sum(out, blocks.rdd.getNumPartitions() if tasks is None else tasks).collect(), RANGE)
    shared.destroy()
    return [{kind.split("/", 1)[1]: v for kind, v in got.items() if kind.split("/", 1)[0] == str(k)} for k in range(len(jobs))]


class BlockDescent:
    """Weights W[l2]: (size, classes) of one projection, for several ridge values at once.

    ``loss``: 'squared' (one Gram matrix for all classes) or 'squared_hinge' (two classes; rows
    whose margin is short take part, a step is halved while the objective rises)."""

    def __init__(self, projection: Projection, classes: int, l2s: Sequence[float], *, block: int = 512, loss: str = "squared"):
        if loss == "squared_hinge" and (classes > 2 or len(l2s) > 1):
            raise ValueError("the squared hinge is solved for two classes and one ridge value at a time")
        self.projection, self.classes, self.l2s, self.block, self.loss = projection, classes, list(l2s), block, loss
        self.columns = 1 if classes <= 2 else classes
        self.weights = {l2: np.zeros((projection.size, self.columns)) for l2 in l2s}
        self.passes = 0
        self.kept: tuple[DataFrame, dict[str, np.ndarray]] | None = None

    def job(self, first: int = 0, count: int = 0) -> tuple:
        return (self.projection, self.weights, self.l2s, self.classes, self.loss == "squared_hinge", self.block, first, count)

    def _next(self) -> tuple[int, int]:
        first = (self.passes * self.block) % self.projection.size
        return first, min(self.block, self.projection.size - first)

    def _read(self, s: dict[str, np.ndarray]) -> dict[float, dict[str, float]]:
        if not s:
            return {v: {"objective": float("nan"), "train_error": float("nan"), "valid_error": float("nan"), "test_error": float("nan")} for v in self.l2s}
        n, share = max(1.0, s["n"][0]), lambda k, i: float(s[f"wrong/{k}"][i] / s["seen"][i]) if s["seen"][i] else float("nan")
        return {v: {"objective": float(s[f"objective/{k}"][0] / n + v * (self.weights[v] ** 2).sum()), "train_error": share(k, 0), "valid_error": share(k, 1), "test_error": share(k, 2)} for k, v in enumerate(self.l2s)}

    def state(self, blocks: DataFrame) -> dict[float, dict[str, float]]:
        """Objective per training row, and the error of every split, of every ridge value."""
        return states(blocks, [self])[0]

    def step(self, blocks: DataFrame) -> None:
        """One pass: solve the next block of features with the others fixed."""
        step_all(blocks, [self])

    @property
    def keeps(self) -> bool:
        """Whether one pass over the data can serve all steps."""
        return self.loss == "squared" and self.projection.size <= KEPT

    def whole(self) -> tuple:
        """The job of that pass: all features at zero weights."""
        none = {0.0: np.zeros((self.projection.size, self.columns))}
        return (self.projection, none, [0.0], self.classes, False, self.block, 0, self.projection.size)

    def _kept(self) -> tuple[np.ndarray, np.ndarray, float]:
        """Gram matrix, product of the features with the targets, and training rows."""
        s, size = self.kept[1], self.projection.size
        return s["gram"].reshape(size, size), s["rhs/0"].reshape(size, self.columns), s["n"][0]

    def sums_of(self, first: int, count: int) -> dict[str, np.ndarray]:
        """What a pass for these features would add up with the present weights."""
        if not self.kept[1]:
            return {}
        gram, rhs, n = self._kept()
        own = slice(first, first + count)
        return {"n": np.asarray([n]), "gram": gram[own, own]} | {f"rhs/{k}": rhs[own] - gram[own] @ self.weights[v] for k, v in enumerate(self.l2s)}

    def objective(self, l2: float) -> float:
        """Objective per training row from the kept sums."""
        if not self.kept[1]:
            return float("nan")
        (gram, rhs, n), w = self._kept(), self.weights[l2]
        left = self.kept[1]["objective/0"][0] - 2 * (w * rhs).sum() + (w * (gram @ w)).sum()
        return float(max(0.0, left) / max(1.0, n) + l2 * (w**2).sum())

    def solve(self, blocks: DataFrame, s: dict[str, np.ndarray], first: int, count: int) -> None:
        self.passes += 1
        if not s or not s["n"][0]:
            return
        gram, n = s["gram"].reshape(count, count), s["n"][0]
        for k, v in enumerate(self.l2s):
            w = self.weights[v][first : first + count]
            rhs = s[f"rhs/{k}"].reshape(count, -1) - v * n * w
            change = np.linalg.solve(gram + v * n * np.eye(count), rhs)
            if self.loss == "squared_hinge":
                before = s[f"objective/{k}"][0] / n + v * (self.weights[v] ** 2).sum()
                for _ in range(8):
                    self.weights[v][first : first + count] = w + change
                    if self.state(blocks)[v]["objective"] <= before + 1e-12:
                        break
                    change = change / 2
                    self.weights[v][first : first + count] = w
            else:
                self.weights[v][first : first + count] = w + change

    def train(self, blocks: DataFrame, cycles: int = 1) -> dict[float, dict[str, float]]:
        for _ in range(cycles * -(-self.projection.size // self.block)):
            self.step(blocks)
        return self.state(blocks)


def states(blocks: DataFrame, descents: Sequence[BlockDescent], tasks: int | None = None) -> list[dict[float, dict[str, float]]]:
    """``BlockDescent.state`` of several projections in one pass."""
    return [d._read(s) for d, s in zip(descents, _pass(blocks, [d.job() for d in descents], tasks), strict=True)]


def step_all(blocks: DataFrame, descents: Sequence[BlockDescent], tasks: int | None = None) -> list[dict[float, dict[str, float]]]:
    """One pass for several projections: each solves its next block.  Returns the states before it."""
    single_thread()
    at = [d._next() for d in descents]
    sums = _pass(blocks.filter("split <> 'test'"), [d.job(*a) for d, a in zip(descents, at, strict=True)], tasks)
    before = [d._read(s) for d, s in zip(descents, sums, strict=True)]
    for d, s, a in zip(descents, sums, at, strict=True):
        d.solve(blocks, s, *a)
    return before


def step_kept(blocks: DataFrame, descents: Sequence[BlockDescent], tasks: int | None = None) -> bool:
    """``step_all`` for descents that keep the sums of ``blocks``; whether a pass was needed for it."""
    single_thread()
    fresh = [d for d in descents if d.kept is None or d.kept[0] is not blocks]
    if fresh:
        for d, s in zip(fresh, _pass(blocks.filter("split = 'train'"), [d.whole() for d in fresh], tasks), strict=True):
            d.kept = (blocks, s)
    for d in descents:
        at = d._next()
        d.solve(blocks, d.sums_of(*at), *at)
    return bool(fresh)


def moments(blocks: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Mean and covariance of the training features, in one pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        single_thread()
        gram, total, n = 0.0, 0.0, 0
        for batch in batches:
            for i in range(batch.num_rows):
                x, _ = matrix(batch, i)
                gram, total, n = gram + x.T @ x, total + x.sum(axis=0), n + len(x)
        if n:
            yield rows_of(TaskContext.get().partitionId(), pieces("gram", gram, RANGE) + pieces("sum", total, RANGE) + pieces("n", np.asarray([float(n)]), RANGE))

    own = blocks.filter("split = 'train'")
    got = gather(tree_sum(own.select("n", "x", "y").mapInArrow(run, SCHEMA), own.rdd.getNumPartitions()).collect(), RANGE)
    if not got:
        return np.zeros(0), np.zeros((0, 0))
    mean = got["sum"] / got["n"][0]
    return mean, got["gram"].reshape(len(mean), -1) / got["n"][0] - np.outer(mean, mean)


def principal(blocks: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Mean, components (columns, by falling variance) and variances of the training features."""
    mean, cov = moments(blocks)
    single_thread()
    values, vectors = np.linalg.eigh(cov)
    signs = np.where(vectors.sum(axis=0) < 0, -1.0, 1.0)
    return mean, (vectors * signs)[:, ::-1], values[::-1]
