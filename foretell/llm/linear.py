"""Sparse linear models on hashed text features, fitted on the driver from a bounded sample.

Features are computed on the executors; the driver gets at most ``MAX_SAMPLE`` rows of hashed
feature numbers, so what it holds has a bound that the data cannot move.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Labelled rows that a fit takes at most (those of smallest hash of their id): a documented bound.
MAX_SAMPLE = 6000


def labelled_sample(docs: DataFrame, labels: DataFrame, columns: Sequence[str], *, id_col: str = "doc_id", text_col: str = "text", most: int = MAX_SAMPLE) -> DataFrame:
    """(id, text, *columns) of at most ``most`` labelled documents, the same in every run.

    Rows with a null label in any of the columns, a null text or a null id are not used; of a
    document labelled more than once the largest labels count.
    """
    rows = labels.select(F.col(id_col).alias("_id"), *[F.col(c).cast("double").alias(f"_label_{c}") for c in columns]).dropna()
    rows = rows.groupBy("_id").agg(*[F.max(f"_label_{c}").alias(f"_label_{c}") for c in columns])
    rows = rows.orderBy(F.xxhash64("_id"), "_id").limit(most)
    texts = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text")).dropna()
    return texts.join(F.broadcast(rows), "_id").dropDuplicates(["_id"])


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


def logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-6, 1 - 1e-6)
    return np.log(p / (1 - p))


class Sparse:
    """Rows of (feature number, value)."""

    def __init__(self, ids: Sequence[np.ndarray], values: Sequence[np.ndarray] | None = None):
        self.rows = np.repeat(np.arange(len(ids)), [len(i) for i in ids])
        self.cols = np.concatenate([*ids, np.empty(0, np.int32)]).astype(np.int64)
        self.vals = np.concatenate([*values, np.empty(0, np.float32)]).astype(np.float64) if values is not None else np.ones(len(self.cols))
        self.n = len(ids)

    def subset(self, keep: np.ndarray) -> Sparse:
        out = object.__new__(Sparse)
        mask = keep[self.rows]
        renumber = np.cumsum(keep) - 1
        out.rows, out.cols, out.vals, out.n = renumber[self.rows[mask]], self.cols[mask], self.vals[mask], int(keep.sum())
        return out

    def only(self, features: np.ndarray) -> Sparse:
        """The same rows with the features where the mask is true."""
        out = object.__new__(Sparse)
        mask = features[self.cols]
        out.rows, out.cols, out.vals, out.n = self.rows[mask], self.cols[mask], self.vals[mask], self.n
        return out

    def dot(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.rows, self.vals * w[self.cols], minlength=self.n)


def log_ratios(x: Sparse, y: np.ndarray, dim: int, smooth: float) -> np.ndarray:
    """Log ratio of each feature's share in the two classes."""
    one = np.bincount(x.cols, x.vals * y[x.rows], minlength=dim) + smooth
    two = np.bincount(x.cols, x.vals * (1 - y)[x.rows], minlength=dim) + smooth
    return np.log(one / one.sum()) - np.log(two / two.sum())


def fit(x: Sparse, y: np.ndarray, dim: int, *, start: np.ndarray, dense: np.ndarray | None = None, l2: float = 1e-3, rate: float = 0.3, steps: int = 80) -> tuple[np.ndarray, float, np.ndarray]:
    """Logistic regression by full gradients with per-coordinate steps, drawn towards ``start``.

    ``dense``: further columns (the probabilities of earlier links of a chain).  Returns the
    weights, the intercept and the weights of the dense columns.
    """
    w, w0 = start.copy(), start
    n = max(1, x.n)
    share = min(max(float(y.mean()) if len(y) else 0.5, 1e-3), 1 - 1e-3)
    b = float(np.log(share / (1 - share)) - (x.dot(w).mean() if x.n else 0.0))
    dense = np.zeros((x.n, 0)) if dense is None else dense
    v = np.zeros(dense.shape[1])
    seen_w, seen_b, seen_v = np.full(dim, 1e-8), 1e-8, np.full(len(v), 1e-8)
    for _ in range(steps if x.n else 0):
        gap = sigmoid(x.dot(w) + b + dense @ v) - y
        g = np.bincount(x.cols, x.vals * gap[x.rows], minlength=dim) / n + l2 * (w - w0)
        gb, gv = float(gap.mean()), dense.T @ gap / n + l2 * v
        seen_w += g * g
        seen_b += gb * gb
        seen_v += gv * gv
        w -= rate * g / np.sqrt(seen_w)
        b -= rate * gb / np.sqrt(seen_b)
        v -= rate * gv / np.sqrt(seen_v)
    return w, b, v


def platt(scores: np.ndarray, y: np.ndarray, steps: int = 200) -> tuple[float, float]:
    """(a, b) of P(1 | score) = sigmoid(a * score + b), by Newton steps on smoothed targets."""
    if not len(y):
        return 1.0, 0.0
    pos, neg = float(y.sum()), float((1 - y).sum())
    t = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    a, b = 1.0, 0.0
    for _ in range(steps):
        p = sigmoid(a * scores + b)
        w = p * (1 - p) + 1e-9
        ga, gb = float(((p - t) * scores).sum()), float((p - t).sum())
        haa, hab, hbb = float((w * scores * scores).sum()) + 1e-6, float((w * scores).sum()), float(w.sum()) + 1e-6
        det = haa * hbb - hab * hab
        da, db = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det
        size = max(1.0, abs(da), abs(db))
        a, b = a - da / size, b - db / size
        if abs(da) + abs(db) < 1e-9:
            break
    return a, b


def folds(n: int, k: int) -> np.ndarray:
    """Fold of each row: by place, so the same in every run."""
    return np.arange(n) % k
