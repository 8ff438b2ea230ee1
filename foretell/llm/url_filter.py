"""URL filtering against a sorted digest array.

Rules are pairs of host and path prefix with a verdict.  Their 64-bit xxhash digests stand
sorted in one memory-mapped file per worker machine, beside the full rule strings.  For a batch
of URLs every (host suffix, path prefix) that could be a rule is digested, probed with one
vectorised binary search, and a digest hit counts only when the stored string is equal too.
The longest rule wins (host and path together; of equal length the longer host).

Defined results: a null URL or one without ``://`` has empty host and path and no rule; URLs
without a rule get the default verdict; repeated rows give repeated rows; an empty rule list
is allowed; rules given twice must agree.
"""

from __future__ import annotations

import hashlib
import os
import tempfile
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes of rules that one index may hold; longer lists are judged in several passes by the caller.
MAX_INDEX_BYTES = 256 << 20

Rule = tuple[str, str, str]  # host, path prefix, verdict


def build_index(rules: Sequence[Rule]) -> bytes:
    """One block of bytes: counts, digests (sorted), string offsets, verdict numbers, path
    lengths in use, strings; verdict names last."""
    by_key: dict[bytes, str] = {}
    for host, path, verdict in rules:
        key = host.encode() + b"\n" + path.encode()
        if by_key.setdefault(key, verdict) != verdict:
            raise ValueError(f"two verdicts for rule {host}{path}")
    verdicts = sorted(set(by_key.values()))
    keyed = sorted((xxhash.xxh64_intdigest(k), k) for k in by_key)
    digests = np.asarray([d for d, _ in keyed], np.uint64)
    offsets = np.cumsum([0, *(len(k) for _, k in keyed)]).astype(np.int64)
    numbers = np.asarray([verdicts.index(by_key[k]) for _, k in keyed], np.int64)
    lengths = np.asarray(sorted({len(k.split(b"\n", 1)[1]) for _, k in keyed}), np.int64)
    names = "\n".join(verdicts).encode()
    head = np.asarray([len(keyed), len(lengths), int(offsets[-1]), len(names)], np.int64)
    out = b"".join(a.tobytes() for a in (head, digests, offsets, numbers, lengths)) + b"".join(k for _, k in keyed) + names
    if len(out) > MAX_INDEX_BYTES:
        raise ValueError(f"the index has {len(out)} bytes; pass at most {MAX_INDEX_BYTES} and chain several filters")
    return out


class Index:
    """A view of a memory-mapped index file."""

    def __init__(self, path: str):
        self.map = np.memmap(path, dtype=np.uint8, mode="r")
        n, m, size, names = (int(x) for x in self.map[:32].view(np.int64))
        at = 32
        self.digests = self.map[at : at + 8 * n].view(np.uint64)
        self.offsets = self.map[at + 8 * n : at + 8 * (2 * n + 1)].view(np.int64)
        self.numbers = self.map[at + 8 * (2 * n + 1) : at + 8 * (3 * n + 1)].view(np.int64)
        self.lengths = [int(x) for x in self.map[at + 8 * (3 * n + 1) : at + 8 * (3 * n + 1 + m)].view(np.int64)]
        at += 8 * (3 * n + 1 + m)
        self.strings = self.map[at : at + size]
        self.verdicts = bytes(self.map[at + size : at + size + names]).decode().split("\n")

    def confirm(self, at: int, digest: int, key: bytes) -> int:
        """Place of the stored string equal to ``key`` among those of this digest, or -1."""
        while at < len(self.digests) and int(self.digests[at]) == digest:
            if bytes(self.strings[self.offsets[at] : self.offsets[at + 1]]) == key:
                return at
            at += 1
        return -1

    def judge(self, hosts: list[str], paths: list[str]) -> list[tuple[str, str] | None]:
        """(rule, verdict) of each URL, or None."""
        keys: list[bytes] = []
        owner: list[int] = []
        for k, (host, path) in enumerate(zip(hosts, paths, strict=True)):
            h, p = host.encode(), path.encode()
            at = 0
            while h:
                suffix = h[at:] + b"\n"
                for n in self.lengths:
                    if n > len(p):
                        break
                    keys.append(suffix + p[:n])
                    owner.append(k)
                at = h.find(b".", at) + 1
                if not at:
                    break
        out: list[tuple[str, str] | None] = [None] * len(hosts)
        if not keys or not len(self.digests):
            return out
        digests = np.fromiter((xxhash.xxh64_intdigest(k) for k in keys), np.uint64, len(keys))
        places = np.searchsorted(self.digests, digests)
        near = np.minimum(places, len(self.digests) - 1)
        best: dict[int, tuple[int, int, int, bytes]] = {}
        for i in np.flatnonzero(self.digests[near] == digests):
            at = self.confirm(int(places[i]), int(digests[i]), keys[i])
            if at >= 0:
                rank = (len(keys[i]), keys[i].index(b"\n"), at, keys[i])
                best[owner[i]] = max(best.get(owner[i], rank), rank)
        for k, (_, _, at, key) in best.items():
            out[k] = (key.replace(b"\n", b"", 1).decode(), self.verdicts[int(self.numbers[at])])
        return out


def _local_file(data: bytes) -> str:
    """A file of this content on this machine; made once, whoever comes first."""
    path = os.path.join(tempfile.gettempdir(), f"url-index-{hashlib.sha256(data).hexdigest()[:32]}")
    if not os.path.exists(path):
        handle, part = tempfile.mkstemp(dir=tempfile.gettempdir())
        with os.fdopen(handle, "wb") as f:
            f.write(data)
        os.replace(part, path)
    return path


def host_and_path(url: str = "url") -> tuple[F.Column, F.Column]:
    """Host and path of a URL column as Spark expressions; both empty for null or no ``://``."""
    whole = F.coalesce(F.col(url), F.lit(""))
    at = F.instr(whole, "://")
    rest = F.when(at > 0, F.substring(whole, at + 3, F.length(whole))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.translate(host, letters, letters.lower()), path


def judge_urls(pages: DataFrame, rules: Sequence[Rule], *, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """One row per page row: id, host, path, rule (or null), verdict."""
    data = pages.sparkSession.sparkContext.broadcast(build_index(rules))
    id_type = pages.schema[id_col].dataType.simpleString()
    host, path = host_and_path(url_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Index(_local_file(data.value))
        for batch in batches:
            found = index.judge(batch.column("host").to_pylist(), batch.column("path").to_pylist())
            rule = pa.array([f[0] if f else None for f in found], pa.string())
            verdict = pa.array([f[1] if f else default for f in found], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("host"), batch.column("path"), rule, verdict], ["id", "host", "path", "rule", "verdict"])

    out = pages.select(F.col(id_col).alias("id"), host.alias("host"), path.alias("path")).mapInArrow(run, f"id {id_type}, host string, path string, rule string, verdict string")
    return out.withColumnRenamed("id", id_col)
