"""Toxicity by a chain of linear classifiers.

Categories are label columns in a fixed order.  Each link is a logistic regression on the
presence of hashed words and word beginnings plus the log-odds of the categories before it;
later links are trained on out-of-fold predictions of the earlier ones, so that what they see
in training is what they will see on new texts.  The features of a link are those whose
presence speaks for the category beyond a fixed chi-square level and log ratio.

The given label table has one toxicity label, so the query's chain is ``low_quality`` (the
complement of the quality label) and then ``toxic``; any number of columns may be chained.

Defined results: a null or empty text gets the chain's intercepts only and is never rejected;
without usable labels every probability is 0; repeated rows give repeated rows.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import linear
from . import textkernel as K

BITS = 20
#: Word beginnings (bytes) that are features beside the whole word.
BEGINNINGS = (4, 5, 6)
#: Chi-square level of a feature, and labelled texts it must stand in at least.
LEVEL, LEAST = 30.0, 4
#: Log ratio of presence in favour of the category from which a feature may be used.
TOWARDS = 2.5
FOLDS = 3
#: Feature numbers that the driver counts at a time.
COUNTED = 1 << 18
THRESHOLD = 0.5


def _slots(c: K.Chunk) -> np.ndarray:
    """(kinds, words) feature numbers of every word."""
    whole = c.word_hashes()
    out = [whole]
    for n in BEGINNINGS:
        cut = np.minimum(c.ends, c.starts + n)
        out.append(np.where(c.ends - c.starts > n, K.mix64(c.span_hashes(c.starts, cut) + np.uint64(n)), whole))
    return (np.stack(out) >> np.uint64(64 - BITS)).astype(np.int32)


def features(column: pa.Array) -> Iterator[np.ndarray]:
    """Per text, its distinct feature numbers."""
    for c in K.chunks(column, lower=True, alnum=True):
        slots = _slots(c)
        for i in range(c.n):
            yield np.unique(slots[:, c.word_offsets[i] : c.word_offsets[i + 1]])


class Chain:
    """Weights of every link: sparse (numbers, weights), intercept, weights of earlier links."""

    def __init__(self, names: Sequence[str], links: list[tuple[np.ndarray, np.ndarray, float, np.ndarray]]):
        self.names, self.links = list(names), links
        self.used = np.unique(np.concatenate([*(ids for ids, *_ in links), np.empty(0, np.int64)]))
        self.table = np.full(1 << BITS, -1, np.int32)
        self.table[self.used] = np.arange(len(self.used))
        self.weights = np.zeros((len(links), len(self.used) + 1))
        for k, (ids, w, _, _) in enumerate(links):
            self.weights[k, self.table[ids]] = w

    def probabilities(self, c: K.Chunk) -> np.ndarray:
        """(texts, categories)."""
        slots, owner = self.table[_slots(c)], c.text_of_word()
        kinds, words = np.nonzero(slots >= 0)
        pairs = np.unique(owner[words] * np.int64(len(self.used) + 1) + slots[kinds, words])
        rows, cols = pairs // (len(self.used) + 1), pairs % (len(self.used) + 1)
        out = np.zeros((c.n, len(self.links)))
        for k, (_, _, bias, earlier) in enumerate(self.links):
            z = np.bincount(rows, self.weights[k, cols], minlength=c.n) + bias
            if k:
                z = z + linear.logit(out[:, :k]) @ earlier
            out[:, k] = linear.sigmoid(z)
        return out


class Presence:
    """Distinct feature numbers of every row, end to end in 32 bits: what the driver holds of the sample.

    No array beside it has an element for each of them, only for those of ``COUNTED`` at a time
    and for those of picked features.
    """

    def __init__(self, ids: Sequence[np.ndarray]):
        self.n = len(ids)
        self.ends = np.cumsum([len(i) for i in ids], dtype=np.int64)
        self.flat = np.concatenate([*ids, np.empty(0, np.int32)])

    def _blocks(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(row, feature number), ``COUNTED`` at a time."""
        for at in range(0, len(self.flat), COUNTED):
            cols = self.flat[at : at + COUNTED]
            yield np.searchsorted(self.ends, np.arange(at, at + len(cols)), side="right"), cols

    def counts(self, group: np.ndarray, n_groups: int) -> np.ndarray:
        """(groups, features): rows of the group that have the feature."""
        out = np.zeros((n_groups, 1 << BITS), np.int32)
        for rows, cols in self._blocks():
            own = group[rows]
            for g in range(n_groups):
                out[g] += np.bincount(cols[own == g], minlength=1 << BITS).astype(np.int32)
        return out

    def only(self, ids: np.ndarray, keep: np.ndarray) -> linear.Sparse:
        """The rows to keep with the features of ``ids`` (ascending), both numbered anew."""
        picked, renumber = np.zeros(1 << BITS, bool), np.cumsum(keep) - 1
        picked[ids] = True
        out = object.__new__(linear.Sparse)
        parts = [(np.empty(0, np.int64), np.empty(0, np.int32))]
        for rows, cols in self._blocks():
            mask = picked[cols] & keep[rows]
            parts.append((renumber[rows[mask]], cols[mask]))
        out.rows, out.cols = np.concatenate([r for r, _ in parts]), np.searchsorted(ids, np.concatenate([c for _, c in parts]))
        out.vals, out.n = np.ones(len(out.cols)), int(keep.sum())
        return out


def _learn(x: Presence, keep: np.ndarray, both: np.ndarray, one: np.ndarray, y: np.ndarray, dense: np.ndarray) -> tuple[np.ndarray, np.ndarray, float, np.ndarray]:
    """Feature numbers, their weights, intercept and weights of ``dense``, from the rows to keep.

    ``both``, ``one``: how many of these rows, and of those of the category, have each feature;
    ``y`` and ``dense`` are of these rows.
    """
    n1, n0 = y.sum(), (1 - y).sum()
    ids = np.flatnonzero(both >= LEAST)
    one, zero = one[ids].astype(np.float64), (both[ids] - one[ids]).astype(np.float64)
    a, b = one, zero
    c, d = n1 - one, n0 - zero
    n = n1 + n0
    chi = n * (a * d - b * c) ** 2 / np.maximum(1e-9, (a + b) * (c + d) * (a + c) * (b + d))
    ratio = np.log((one + 0.5) / (n1 + 1)) - np.log((zero + 0.5) / (n0 + 1))
    picked = (chi >= LEVEL) & (ratio > TOWARDS)
    ids, ratio = ids[picked], ratio[picked]
    own = x.only(ids, keep)  # few features are left: fit in their own numbering
    start = ratio * max(0.0, linear.platt(own.dot(ratio), y)[0])
    w, bias, v = linear.fit(own, y, len(ids), start=start, dense=dense, l2=1e-4, rate=0.1, steps=100)
    return ids, w, bias, v


def fit_chain(x: Presence, marks: Sequence[np.ndarray], categories: Sequence[str]) -> Chain | None:
    """The chain of the categories whose 0 and 1 of every row are ``marks``; None when one lacks a class."""
    fold = linear.folds(x.n, FOLDS)
    everything, have = np.ones(x.n, bool), x.counts(fold, FOLDS)
    seen = np.zeros((x.n, 0))  # log-odds of earlier links, out of fold
    links = []
    for y in marks:
        if not 0 < y.sum() < len(y):
            return None
        held = np.full(x.n, y.mean())
        of_one = x.counts(np.where(y > 0, fold, FOLDS), FOLDS)
        both, one = have.sum(0, dtype=np.int32), of_one.sum(0, dtype=np.int32)
        for f in range(FOLDS):
            own = fold != f
            if 0 < y[own].sum() < own.sum():
                ids, w, b, v = _learn(x, own, both - have[f], one - of_one[f], y[own], seen[own])
                held[~own] = linear.sigmoid(x.only(ids, ~own).dot(w) + b + seen[~own] @ v)
        ids, w, b, v = _learn(x, everything, both, one, y, seen)
        links.append((ids[w != 0], w[w != 0], b, v))
        seen = np.column_stack((seen, linear.logit(held)))
    return Chain(categories, links)


def train(docs: DataFrame, labels: DataFrame, categories: Sequence[str], *, id_col: str = "doc_id", text_col: str = "text", most: int = linear.MAX_SAMPLE) -> Chain | None:
    """Fit the chain on at most ``most`` labelled rows; None when a category lacks a class."""
    sample = linear.labelled_sample(docs, labels, categories, id_col=id_col, text_col=text_col, most=most)
    id_type = docs.schema[id_col].dataType.simpleString()
    marks = [f"_label_{c}" for c in categories]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = pa.array([i.astype(np.int32).tobytes() for i in features(batch.column("_text"))], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("_id"), *[batch.column(m) for m in marks], ids], ["id", *marks, "ids"])

    rows = sample.select("_id", *marks, "_text").mapInArrow(run, f"id {id_type}, {', '.join(f'{m} double' for m in marks)}, ids binary").toArrow()
    id_of = rows.column("id").to_pylist()
    order = sorted(range(len(id_of)), key=lambda k: id_of[k])
    x = Presence([np.frombuffer(i.as_buffer(), np.int32) for i in map(list(rows.column("ids")).__getitem__, order)])
    ys = [(rows.column(m).to_numpy()[order] > 0).astype(np.float64) for m in marks]
    del rows
    return fit_chain(x, ys, categories)


def with_complement(labels: DataFrame) -> DataFrame:
    """doc_id, low_quality, toxic of the given label table."""
    return labels.select("doc_id", (1 - F.col("quality")).alias("low_quality"), "toxic")


def score(docs: DataFrame, chain: Chain | None, categories: Sequence[str], *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document row: id and p_<category> of each link."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)
    id_type = docs.schema[id_col].dataType.simpleString()
    names = [f"p_{c}" for c in categories]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            p = _batch(m, batch.column("text"), len(names))
            yield pa.RecordBatch.from_arrays([batch.column("id"), *[pa.array(p[:, k]) for k in range(len(names))]], ["id", *names])

    out = docs.selectExpr(f"`{id_col}` as id", f"`{text_col}` as text").mapInArrow(run, f"id {id_type}, {', '.join(f'{n} double' for n in names)}")
    return out.withColumnRenamed("id", id_col)


def _batch(chain: Chain | None, column: pa.Array, width: int) -> np.ndarray:
    parts = [chain.probabilities(c) if chain is not None else np.zeros((c.n, width)) for c in K.chunks(column, lower=True, alnum=True)]
    return np.concatenate([*parts, np.zeros((0, width))])


def without_toxic(docs: DataFrame, chain: Chain | None, *, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs``, all their columns, whose last category stays below the threshold."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            yield batch.filter(pa.array(_batch(m, batch.column(text_col), 1 if m is None else len(m.links))[:, -1] < threshold))

    return docs.mapInArrow(run, docs.schema)
