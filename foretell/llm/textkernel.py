"""Vectorised word and shingle arithmetic over Arrow string columns.

Everything works on the UTF-8 bytes of a whole batch of texts at once: a text is a
slice of one byte array, words and shingles are index arrays.  Texts are never cut;
a batch is walked in chunks of whole texts so that the scratch arrays stay small.
Nulls count as empty texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at a time (one longer text forms a chunk of its own).
CHUNK_BYTES = 512 << 10

_U = np.uint64
_RADIX = _U(0x9E3779B97F4A7C15 | 1)


def _radix_inverse() -> np.uint64:
    """Inverse of the odd radix modulo 2**64 by Newton's iteration."""
    r, x = int(_RADIX), 1
    for _ in range(6):
        x = x * (2 - r * x) % (1 << 64)
    return _U(x)


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), elementwise."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_BYTE_CODE = mix64(np.arange(1, 257, dtype=np.uint64) * _U(0xD1342543DE82EF95))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: Bytes that are neither ASCII digits, ASCII lower-case letters nor part of a non-ASCII character.
_NOT_ALNUM = np.ones(256, dtype=bool)
_NOT_ALNUM[0x30:0x3A] = _NOT_ALNUM[0x61:0x7B] = _NOT_ALNUM[0x80:] = False

_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, CHUNK_BYTES + 1)
        for i, base in enumerate((_RADIX, _radix_inverse())):
            steps = np.full(size, base, dtype=np.uint64)
            steps[0] = 1
            _powers[i] = np.cumprod(steps, dtype=np.uint64)
    return _powers[0][:n], _powers[1][:n]


class Chunk:
    """Whole texts of rows ``first .. first + n - 1`` of a batch, as bytes and word spans."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, first: int, separators: np.ndarray, lower: bool):
        self.first, self.n = first, len(offsets) - 1
        self.raw, self.offsets = data, offsets
        self.data = _LOWER[data] if lower else data
        inside = ~separators[self.data]
        before = np.empty_like(inside)
        after = np.empty_like(inside)
        if len(inside):
            before[0], before[1:] = False, inside[:-1]
            after[-1], after[:-1] = False, inside[1:]
            full = offsets[1:] > offsets[:-1]
            before[offsets[:-1][full]] = False
            after[offsets[1:][full] - 1] = False
        self.inside = inside
        self.starts = np.flatnonzero(inside & ~before)
        self.ends = np.flatnonzero(inside & ~after) + 1
        #: word_offsets[i] .. word_offsets[i + 1]: the words of text i
        self.word_offsets = np.searchsorted(self.starts, offsets)

        self._sums: np.ndarray | None = None

    def span_hashes(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """64-bit hash of the bytes of each span, equal for equal bytes in any chunk."""
        if not len(starts):
            return np.empty(0, np.uint64)
        up, down = _power_tables(len(self.data) + 1)
        if self._sums is None:
            self._sums = np.zeros(len(self.data) + 1, np.uint64)
            np.cumsum(_BYTE_CODE[self.data] * up[:-1], out=self._sums[1:])
        h = (self._sums[ends] - self._sums[starts]) * down[starts]
        return mix64(h + (ends - starts).astype(np.uint64) * _U(0xA0761D6478BD642F))

    def word_hashes(self) -> np.ndarray:
        return self.span_hashes(self.starts, self.ends)


    def characters(self) -> tuple[np.ndarray, np.ndarray]:
        """Byte offsets of all characters and, last, of the end; and the numbers of each text's first
        character and, last, of all characters."""
        starts = np.flatnonzero((self.data & 0xC0) != 0x80)
        return np.append(starts, len(self.data)), np.searchsorted(starts, self.offsets)

    def character_gram_hashes(self, n: int, places: np.ndarray) -> np.ndarray:
        """Hash of the ``n`` characters from each character on (the last n - 1 of the chunk left out)."""
        return self.span_hashes(places[: len(places) - n], places[n:]) if len(places) > n else np.empty(0, np.uint64)

    def per_text(self, flags: np.ndarray) -> np.ndarray:
        """Sum of a per-byte array over each text."""
        sums = np.concatenate((np.zeros(1, np.float64 if flags.dtype.kind == "f" else np.int64), np.cumsum(flags)))
        return sums[self.offsets[1:]] - sums[self.offsets[:-1]]

    def text_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(self.n), np.diff(self.word_offsets))


def ngram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of ``n`` consecutive word hashes (length len(words) - n + 1)."""
    count = len(words) - n + 1
    if count <= 0:
        return np.empty(0, np.uint64)
    g = words[:count].copy()
    for k in range(1, n):
        g = mix64(g * _U(0xE7037ED1A0B428DB) + words[k : k + count])
    return g


def sequence_hash(words: np.ndarray) -> np.uint64:
    """Hash of a whole (short) sequence of word hashes."""
    g = _U(len(words))
    with np.errstate(over="ignore"):
        for w in words:
            g = mix64(np.asarray([g * _U(0xE7037ED1A0B428DB) + w]))[0]
    return g


def chunks(column: pa.Array | pa.ChunkedArray, *, lower: bool = False, alnum: bool = False) -> Iterator[Chunk]:
    """Chunks of whole texts.  Words are runs of bytes outside space and \\t-\\r, or with
    ``alnum`` runs of ASCII letters and digits and non-ASCII characters."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = pc.fill_null(column, "")
    _, offs, body = column.buffers()
    offsets = np.frombuffer(offs, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(body, dtype=np.uint8) if body is not None else np.empty(0, np.uint8)
    separators = _NOT_ALNUM if alnum else _SPACE
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + CHUNK_BYTES, side="right")) - 1)
        j = min(j, len(column))
        yield Chunk(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], i, separators, lower)
        i = j


def shingle_sets(column: pa.Array, n: int, *, lower: bool = True) -> Iterator[np.ndarray]:
    """Per text, in order, the sorted distinct 64-bit hashes of its ``n``-word shingles; a
    text of fewer words has its whole sequence as one; a text without words has none."""
    for c in chunks(column, lower=lower):
        hashes = c.word_hashes()
        grams = ngram_hashes(hashes, n)
        for k in range(c.n):
            a, b = int(c.word_offsets[k]), int(c.word_offsets[k + 1])
            if b - a >= n:
                yield np.unique(grams[a : b - n + 1])
            elif b > a:
                yield np.asarray([sequence_hash(hashes[a:b])], np.uint64)
            else:
                yield np.empty(0, np.uint64)
