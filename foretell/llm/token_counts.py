"""Token counts of a public byte-pair vocabulary without emitting identifiers.

The vocabulary file's own rules are followed: special strings standing in a text are one
token each; the rest is composed (NFC), lower-cased, cut into words by the file's pattern and
merged as bytes with an end-of-word mark.  Merging keeps the symbols of a word in a linked
list and the adjacent pairs in a heap: the pair of lowest rank is popped until none is left,
and the count is initial symbols minus merges.

Defined results: null and empty texts have 0 tokens; repeated rows give repeated rows; texts
are never cut, and one text's words are counted through a memory of bounded size.
"""

from __future__ import annotations

import heapq
import json
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame

#: Words whose counts a worker remembers at most; beyond it the memory starts anew.
MEMORY_WORDS = 300_000
#: Characters of a text that are cut into words at a time.
PIECE_CHARS = 1 << 20

#: Fixed values of the vocabulary format: visible stand-ins of the 256 bytes are the printable
#: Latin-1 characters themselves, the other bytes follow from code point 256 on.
_PRINTABLE = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]


def _byte_names() -> list[str]:
    names, spare = [""] * 256, 256
    for b in range(256):
        if b in _PRINTABLE:
            names[b] = chr(b)
        else:
            names[b], spare = chr(spare), spare + 1
    return names


class Merger:
    """Counts tokens by the merges of a tokenizer file (the parts of it that bear on counts)."""

    def __init__(self, spec: dict):
        self.suffix = spec["suffix"]
        #: (left, right) -> (rank, merged symbol)
        self.merges = {(a, b): (k, a + b) for k, (a, b) in enumerate(spec["merges"])}
        self.names = _byte_names()
        self.words = regex.compile(spec["pattern"])
        self.special = regex.compile("|".join(map(regex.escape, sorted(spec["special"], key=len, reverse=True)))) if spec["special"] else None
        self.memory: dict[str, int] = {}

    def word(self, word: str) -> int:
        """Tokens of one word."""
        symbols = [self.names[b] for b in word.encode()]
        symbols[-1] += self.suffix
        n = len(symbols)
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        heap = [(m[0], i, symbols[i], symbols[i + 1]) for i in range(n - 1) if (m := self.merges.get((symbols[i], symbols[i + 1])))]
        heapq.heapify(heap)
        left = n
        while heap:
            _, i, a, b = heapq.heappop(heap)
            j = after[i]
            if symbols[i] != a or j < 0 or symbols[j] != b:
                continue  # one of the two has been merged meanwhile
            symbols[i], symbols[j] = a + b, ""
            left -= 1
            after[i] = k = after[j]
            if k >= 0:
                before[k] = i
                if m := self.merges.get((symbols[i], symbols[k])):
                    heapq.heappush(heap, (m[0], i, symbols[i], symbols[k]))
            if (h := before[i]) >= 0 and (m := self.merges.get((symbols[h], symbols[i]))):
                heapq.heappush(heap, (m[0], h, symbols[h], symbols[i]))
        return left

    def _plain(self, text: str) -> int:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # the library lower-cases each letter by itself
        text = text.lower()
        total, memory, at = 0, self.memory, 0
        while at < len(text):
            end = at + PIECE_CHARS
            if end < len(text):
                while end < len(text) and not (text[end - 1] == " " or text[end] == " "):
                    end += 1  # no word spans a blank
            for w in self.words.findall(text, at, end):
                c = memory.get(w)
                if c is None:
                    if len(memory) >= MEMORY_WORDS:
                        memory.clear()
                    c = self.word(w)
                    if len(w) < 64:
                        memory[w] = c
                total += c
            at = end
        return total

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if self.special is None or "<" not in text:
            return self._plain(text)
        total, at = 0, 0
        for m in self.special.finditer(text):
            total += self._plain(text[at : m.start()]) + 1
            at = m.end()
        return total + self._plain(text[at:])


def load(path: str) -> dict:
    """The parts of a tokenizer file that counts depend on; raises for other kinds of file."""
    with open(path, encoding="utf-8") as f:
        d = json.load(f)
    steps = d["pre_tokenizer"]["pretokenizers"]
    split = next(s for s in steps if s["type"] == "Split")
    if d["model"]["type"] != "BPE" or not split["invert"] or split["behavior"] != "Removed":
        raise ValueError(f"not a byte-pair vocabulary with a word pattern: {path}")
    # white space by Unicode's property, as the library's pattern engine has it
    pattern = split["pattern"]["Regex"].replace("\\s", "\\p{White_Space}")
    return {"merges": [tuple(m) for m in d["model"]["merges"]], "suffix": d["model"]["end_of_word_suffix"] or "", "pattern": pattern, "special": [t["content"] for t in d["added_tokens"]]}


_ready: dict[str, Merger] = {}


def count_tokens(docs: DataFrame, vocabulary: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document row: id, n_bytes, n_tokens.  ``vocabulary``: path on the driver;
    its merges (of fixed size) are broadcast."""
    shared = docs.sparkSession.sparkContext.broadcast(load(vocabulary))
    id_type = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if vocabulary not in _ready:
            _ready[vocabulary] = Merger(shared.value)
        merger = _ready[vocabulary]
        for batch in batches:
            text = pc.fill_null(batch.column("text"), "")
            n = pa.array([merger.count(t.as_py()) for t in text], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("id"), pc.binary_length(text).cast(pa.int64()), n], ["id", "n_bytes", "n_tokens"])

    out = docs.selectExpr(f"`{id_col}` as id", f"`{text_col}` as text").mapInArrow(run, f"id {id_type}, n_bytes long, n_tokens long")
    return out.withColumnRenamed("id", id_col)
