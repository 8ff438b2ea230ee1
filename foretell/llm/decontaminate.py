"""Benchmark decontamination with one Aho-Corasick automaton over normalised test questions and answers.

Words are runs of ASCII letters and digits (A-Z lower-cased) and non-ASCII characters.  Each
item gives its windows of ``window`` consecutive words; a shorter item is one window, an item
without words none.  The automaton runs over word numbers rather than characters, so a text is
scanned once and every match already ends on a word; word numbers map back to the byte offsets
of the original text.

The automaton does not hold every window.  An item is cut into even blocks of half a window, and
those are its patterns: every window has one of them whole inside it.  Where a block is met in a
text, the agreement of text and item is followed to both sides; when it is a window long, all its
words are hit.  So an automaton has about one node a word of the benchmark.

Defined results: a null or empty text has no words and no hits; null item texts and items
without words never match; repeated items count apart (by ``item_id``); repeated documents
give repeated rows; an empty benchmark leaves every document clean.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K

WINDOW = 10
#: Words of the benchmark that one automaton is aimed at (about 200 bytes each); a larger benchmark is
#: scanned for in several passes, and the driver holds the items of one of them at a time.
MAX_AUTOMATON_WORDS = 1 << 20

_WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
SPANS = "array<struct<first_word:int,last_word:int,start:long,stop:long>>"


class Automaton:
    """Blocks of a bounded set of items, as word-number sequences."""

    def __init__(self, items: list[tuple[object, str]], window: int):
        column = pa.array([t for _, t in items], pa.large_string())
        seqs: list[np.ndarray] = []
        for c in K.chunks(column, lower=True, alnum=True):
            h = c.word_hashes()
            seqs += [h[c.word_offsets[i] : c.word_offsets[i + 1]] for i in range(c.n)]
        self.vocabulary = np.unique(np.concatenate([*seqs, np.empty(0, np.uint64)]))
        self.items, self.window = [str(i) for i, _ in items], window
        self.words = [(np.searchsorted(self.vocabulary, s) + 1).astype(np.int32) for s in seqs]
        size = max(1, window // 2)
        places: dict[tuple[int, ...], list[tuple[int, int]]] = {}
        for k, w in enumerate(self.words):
            ids = tuple(w.tolist())
            for a in range(0, len(ids) - size + 1, size) if len(ids) >= size else range(min(1, len(ids))):
                places.setdefault(ids[a : a + size], []).append((k, a))
        self.trie = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
        for block, where in places.items():
            self.trie.add_word(block, (len(block), where))
        self.empty = not places
        if not self.empty:
            self.trie.make_automaton()

    def numbers(self, hashes: np.ndarray) -> np.ndarray:
        """1 + place in the vocabulary, 0 for other words."""
        if not len(self.vocabulary) or not len(hashes):
            return np.zeros(len(hashes), np.int32)
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)
        return np.where(self.vocabulary[at] == hashes, at + 1, 0).astype(np.int32)

    def scan(self, numbers: np.ndarray) -> tuple[np.ndarray, set[int]]:
        """Which words of one text are hit, and the items whose windows occur in it."""
        hit = np.zeros(len(numbers), bool)
        found: set[int] = set()
        if not self.empty and numbers.any():
            reached: dict[tuple[int, int], int] = {}
            for end, (size, where) in self.trie.iter(tuple(numbers.tolist())):
                first = end - size + 1
                for k, a in where:
                    # blocks of one agreement lie on one diagonal; it is followed once
                    if reached.get((k, first - a), -1) >= end:
                        continue
                    item = self.words[k]
                    left = _agreement(numbers[max(0, first - a) : first][::-1], item[max(0, a - first) : a][::-1])
                    right = _agreement(numbers[end + 1 : end + 1 + len(item) - a - size], item[a + size :][: len(numbers) - end - 1])
                    reached[k, first - a] = end + right
                    if left + size + right >= min(self.window, len(item)):
                        hit[first - left : end + right + 1] = True
                        found.add(k)
        return hit, found


def _agreement(a: np.ndarray, b: np.ndarray) -> int:
    """How many leading elements of two arrays of one length are equal."""
    same = a == b
    stop = int(same.argmin()) if len(same) else 0
    return len(same) if len(same) and same[stop] else stop


def _runs(hit: np.ndarray) -> np.ndarray:
    """First and last index of each run of true values."""
    edge = np.diff(np.concatenate(([0], hit.astype(np.int8), [0])))
    return np.stack((np.flatnonzero(edge == 1), np.flatnonzero(edge == -1) - 1), axis=1)


def _items(benchmark: DataFrame, item_col: str, text_col: str) -> DataFrame:
    return benchmark.select(F.col(item_col).alias("item"), F.col(text_col).alias("text")).where("text is not null")


def _part_count(items: DataFrame, most: int) -> int:
    """Parts of about half of ``most`` words, or one when all words fit."""
    words = items.agg(F.sum(F.regexp_count("text", F.lit(_WORD))).alias("s")).first()["s"] or 0
    return 1 if words <= most else -(-2 * int(words) // most)


def _part(items: DataFrame, k: int, count: int) -> list[tuple[object, str]]:
    """The items of part ``k``, which their texts decide; nothing else is held on the driver."""
    own = items if count == 1 else items.filter(F.pmod(F.xxhash64("text"), F.lit(count)) == k)
    return [(r["item"], r["text"]) for r in own.collect()]


_cache: dict[object, Automaton] = {}


def scan(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, max_words: int = MAX_AUTOMATON_WORDS) -> DataFrame:
    """One row per document row: id, n_words, n_hit, items (sorted strings), spans.

    ``spans`` are the maximal runs of hit words with the byte offsets of the original text.
    The documents are not shuffled.  Each pass has one automaton of about ``max_words`` words of
    items; when the benchmark is larger, further passes carry the hits on in the same rows.
    """
    given = _items(benchmark, item_col, item_text_col)
    count = _part_count(given, max_words)
    spark = docs.sparkSession
    id_type = docs.schema[id_col].dataType.simpleString()
    frame = docs.selectExpr(f"`{id_col}` as id", f"`{text_col}` as text", f"cast(null as {SPANS}) as spans", "cast(null as array<string>) as items")
    for k in range(count):
        last = k == count - 1
        shared, key = spark.sparkContext.broadcast(_part(given, k, count)), uuid.uuid4().hex
        schema = f"id {id_type}, text string, spans {SPANS}, items array<string>, n_words long, n_hit long"

        def run(batches: Iterator[pa.RecordBatch], shared=shared, key=key, last=last) -> Iterator[pa.RecordBatch]:
            if key not in _cache:
                _cache.clear()
                _cache[key] = Automaton(shared.value, window)
            automaton = _cache[key]
            for batch in batches:
                out: dict[str, list] = {"spans": [], "items": [], "n_words": [], "n_hit": []}
                before, named, row = batch.column("spans").to_pylist(), batch.column("items").to_pylist(), 0
                for c in K.chunks(batch.column("text"), lower=True, alnum=True):
                    numbers = automaton.numbers(c.word_hashes())
                    for i in range(c.n):
                        a, b = int(c.word_offsets[i]), int(c.word_offsets[i + 1])
                        hit, found = automaton.scan(numbers[a:b])
                        for s in before[row] or ():
                            hit[s["first_word"] : s["last_word"] + 1] = True
                        base = int(c.offsets[i])
                        out["spans"].append([{"first_word": int(x), "last_word": int(y), "start": int(c.starts[a + x]) - base, "stop": int(c.ends[a + y]) - base} for x, y in _runs(hit)])
                        out["items"].append(sorted({*(named[row] or ()), *(automaton.items[f] for f in found)}))
                        out["n_words"].append(b - a)
                        out["n_hit"].append(int(hit.sum()))
                        row += 1
                text = pa.nulls(batch.num_rows, pa.string()) if last else batch.column("text")
                yield pa.RecordBatch.from_arrays([batch.column("id"), text, pa.array(out["spans"], _SPANS_ARROW), pa.array(out["items"], pa.list_(pa.string())), pa.array(out["n_words"], pa.int64()), pa.array(out["n_hit"], pa.int64())], ["id", "text", "spans", "items", "n_words", "n_hit"])

        frame = frame.select("id", "text", "spans", "items").mapInArrow(run, schema)
    return frame.selectExpr(f"id as `{id_col}`", "n_words", "n_hit", "items", "spans")


_SPANS_ARROW = pa.list_(pa.struct([("first_word", pa.int32()), ("last_word", pa.int32()), ("start", pa.int64()), ("stop", pa.int64())]))


def clean_documents(docs: DataFrame, benchmark: DataFrame, *, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, max_words: int = MAX_AUTOMATON_WORDS) -> DataFrame:
    """The rows of ``docs`` (all their columns) in which no window of the benchmark occurs.

    Whole record batches are filtered, so columns of any name and repeated rows pass through.
    """
    spark = docs.sparkSession
    frame = docs
    given = _items(benchmark, item_col, item_text_col)
    count = _part_count(given, max_words)
    for k in range(count):
        shared, key = spark.sparkContext.broadcast(_part(given, k, count)), uuid.uuid4().hex

        def run(batches: Iterator[pa.RecordBatch], shared=shared, key=key) -> Iterator[pa.RecordBatch]:
            if key not in _cache:
                _cache.clear()
                _cache[key] = Automaton(shared.value, window)
            automaton = _cache[key]
            for batch in batches:
                keep: list[bool] = []
                for c in K.chunks(batch.column(text_col), lower=True, alnum=True):
                    numbers = automaton.numbers(c.word_hashes())
                    keep += [not automaton.scan(numbers[c.word_offsets[i] : c.word_offsets[i + 1]])[1] for i in range(c.n)]
                yield batch.filter(pa.array(keep, pa.bool_()))

        frame = frame.mapInArrow(run, docs.schema)
    return frame
