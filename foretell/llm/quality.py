"""Quality rules: base statistics and a calibrated hashed n-gram classifier.

The classifier is a logistic regression on the shares of hashed word 1- and 2-grams and character
3- and 4-grams (of code points), fitted on a bounded sample of labelled rows (``most``),
calibrated by a sigmoid on out-of-fold scores and compared with a fixed threshold.  Statistics and
scores come from one pass over the whole texts in Arrow batches.

Defined results: a null or empty text has statistics 0, fails the base rule and is not kept;
without usable labels the classifier says 1 for every text, so only the base rule decides;
repeated rows give repeated rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import linear
from . import textkernel as K

BITS = 18
WORD_GRAMS, CHARACTER_GRAMS = (1, 2), (3, 4)
#: Share of a text's n-grams times this is a feature's value (keeps values near 1).
SCALE = 20.0
#: Probability of good quality from which a text is kept (fixed).
THRESHOLD = 0.2
#: Fixed values of the base rule.
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True


def _slots(hashes: np.ndarray, salt: int) -> np.ndarray:
    return ((hashes ^ np.uint64(salt * 0x9E3779B97F4A7C15 % (1 << 64))) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(64 - BITS)).astype(np.int32)


def _groups(c: K.Chunk) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Per kind of n-gram: slots, and first and last-plus-one n-gram of every text."""
    words = c.word_hashes()
    for n in WORD_GRAMS:
        first, stop = c.word_offsets[:-1], np.maximum(c.word_offsets[:-1], c.word_offsets[1:] - n + 1)
        yield _slots(K.ngram_hashes(words, n), n), first, stop
    places, owner = c.characters()
    for n in CHARACTER_GRAMS:
        first, stop = owner[:-1], np.maximum(owner[:-1], owner[1:] - n + 1)
        yield _slots(c.character_gram_hashes(n, places), 16 + n), first, stop


def features(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Per text: distinct slots and their values."""
    for c in K.chunks(column):
        parts = list(_groups(c))
        for i in range(c.n):
            own = np.concatenate([s[a[i] : b[i]] for s, a, b in parts])
            ids, n = np.unique(own, return_counts=True)
            yield ids, (n * (SCALE / max(1, len(own)))).astype(np.float32)


def scores(c: K.Chunk, weights: np.ndarray) -> np.ndarray:
    """Dot product of each text's features with the weights."""
    total, count = np.zeros(c.n), np.zeros(c.n, np.int64)
    for slots, first, stop in _groups(c):
        sums = np.concatenate(([0.0], np.cumsum(weights[slots])))
        total += np.where(stop > first, sums[np.minimum(stop, len(slots))] - sums[np.minimum(first, len(slots))], 0.0)
        count += stop - first
    return total * SCALE / np.maximum(1, count)


def statistics(c: K.Chunk) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of every text."""
    out = {"n_words": np.diff(c.word_offsets)}
    out["word_chars"] = c.per_text(c.inside & ((c.data & 0xC0) != 0x80))
    out["n_symbols"] = c.per_text(_SYMBOL[c.data])
    # lines: cut at newlines and at text ends
    text_starts, text_ends = c.offsets[:-1], c.offsets[1:]
    breaks = np.flatnonzero(c.data == 10)
    starts, ends = np.sort(np.concatenate((text_starts, breaks + 1))), np.sort(np.concatenate((text_ends, breaks)))
    inside = np.concatenate(([0], np.cumsum(c.inside)))
    worded = inside[ends] > inside[starts]
    starts, ends = starts[worded], ends[worded]
    owner = np.searchsorted(text_starts, starts, side="right") - 1
    keys = K.mix64(c.span_hashes(starts, ends) + owner.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))
    _, first = np.unique(keys, return_index=True)
    again = np.ones(len(keys), np.int64)
    again[first] = 0
    out["n_dup_lines"] = np.bincount(owner, again, minlength=c.n).astype(np.int64)
    # words inside three-word windows that the text has twice or more
    words, owner = c.word_hashes(), c.text_of_word()
    grams = K.ngram_hashes(words, 3)
    own = owner[: len(grams)] == owner[2 : 2 + len(grams)]
    keys = K.mix64(grams + owner[: len(grams)].astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))[own]
    _, place, count = np.unique(keys, return_inverse=True, return_counts=True)
    at = np.flatnonzero(own)[count[place] > 1]
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + 3, -1)
    covered = np.cumsum(edge[:-1]) > 0
    out["n_repeat_words"] = np.bincount(owner, covered, minlength=c.n).astype(np.int64)
    return out


class Model:
    def __init__(self, weights: np.ndarray, bias: float, a: float, b: float):
        self.weights, self.bias, self.a, self.b = weights, bias, a, b

    def probability(self, c: K.Chunk) -> np.ndarray:
        return linear.sigmoid(self.a * (scores(c, self.weights) + self.bias) + self.b)


def _learn(x: linear.Sparse, y: np.ndarray) -> tuple[np.ndarray, float]:
    dim = 1 << BITS
    start = linear.log_ratios(x, y, dim, smooth=0.02) / SCALE * 4
    w, b, _ = linear.fit(x, y, dim, start=start, rate=0.1, steps=40)
    return w, b


def train(docs: DataFrame, labels: DataFrame, *, label: str = "quality", id_col: str = "doc_id", text_col: str = "text", most: int = 3000) -> Model | None:
    """Fit on at most ``most`` labelled rows; None when both classes are not there."""
    sample = linear.labelled_sample(docs, labels, [label], id_col=id_col, text_col=text_col, most=most)
    id_type = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = list(features(batch.column("_text")))
            yield pa.RecordBatch.from_arrays([batch.column("_id"), batch.column(f"_label_{label}"), pa.array([i.astype(np.int32).tobytes() for i, _ in found], pa.binary()), pa.array([v.tobytes() for _, v in found], pa.binary())], ["id", "y", "ids", "vals"])

    rows = sample.select("_id", f"_label_{label}", "_text").mapInArrow(run, f"id {id_type}, y double, ids binary, vals binary").toArrow().to_pydict()
    order = sorted(range(len(rows["id"])), key=lambda k: rows["id"][k])
    y = np.asarray([float(rows["y"][k] > 0) for k in order])
    if not 0 < y.sum() < len(y):
        return None
    x = linear.Sparse([np.frombuffer(rows["ids"][k], np.int32) for k in order], [np.frombuffer(rows["vals"][k], np.float32) for k in order])
    del rows
    fold, held = linear.folds(len(y), 3), np.zeros(len(y))
    for f in range(3):
        own = fold != f
        if 0 < y[own].sum() < own.sum():
            w, b = _learn(x.subset(own), y[own])
            held[~own] = x.subset(~own).dot(w) + b
    a, c = linear.platt(held, y)
    w, b = _learn(x, y)
    return Model(w.astype(np.float64), b, a, c)


def judge(docs: DataFrame, model: Model | None, *, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """One row per document row: id, the statistics, base_failed, probability, kept."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    id_type = docs.schema[id_col].dataType.simpleString()
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            got: dict[str, list[np.ndarray]] = {k: [] for k in [*names, "p"]}
            for c in K.chunks(batch.column("text")):
                for k, v in statistics(c).items():
                    got[k].append(v)
                got["p"].append(m.probability(c) if m is not None else np.ones(c.n))
            cols = {k: np.concatenate([*v, np.empty(0, np.float64 if k == "p" else np.int64)]) for k, v in got.items()}
            failed = (cols["n_words"] < MIN_WORDS) | (100 * cols["n_repeat_words"] > MAX_REPEAT_PERCENT * cols["n_words"])
            yield pa.RecordBatch.from_arrays([batch.column("id"), *[pa.array(cols[k].astype(np.int64)) for k in names], pa.array(failed), pa.array(cols["p"]), pa.array(~failed & (cols["p"] >= threshold))], ["id", *names, "base_failed", "probability", "kept"])

    out = docs.selectExpr(f"`{id_col}` as id", f"`{text_col}` as text").mapInArrow(run, f"id {id_type}, {', '.join(f'{k} long' for k in names)}, base_failed boolean, probability double, kept boolean")
    return out.withColumnRenamed("id", id_col)
