"""Language identification of pages by Bayesian evidence fusion.

Four kinds of evidence are multiplied: the likelihood of the visible text under byte-trigram
models of the languages, the language declared in the markup, and a prior of the page's host.
How far a declaration can be trusted, and what a host, its domain and its address suffix speak,
is measured on the pages themselves by grouped aggregation of text-only posteriors: the last label
of an address is smoothed towards all pages, its last two labels towards that, its last three
towards those, the host towards its last three, and a page's own contribution is taken out of its
host before it is used.

The trigram models (of characters) are fitted on a bounded sample of documents of every known
language (``MAX_SAMPLE``); counts over pages cover all pages.

Defined results: a null page or one without text is judged by markup and address alone; a null
or odd address belongs to the host named by the empty string; repeated rows give repeated rows;
without documents of known language the result is empty of languages (null).
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import materialise, salted_join
from .url_filter import host_and_path

#: Documents that the fit is aimed at for each language (those of smallest hash of their id).
MAX_SAMPLE = 1000
#: Languages whose models (256 KB each) fit a worker; with more, fitting raises an error.
MAX_LANGUAGES = 1024
BITS = 16
#: A text's trigrams hang together; of n the weight of n / (1 + n / EFFECTIVE) independent ones is counted.
EFFECTIVE = 60
#: Numbers of last labels of an address that make its levels, the widest first.
LEVELS = (1, 2, 3)
#: Pages that a parent level is worth in smoothing.
SMOOTH = 5.0

_ASCII_LOWER = {c: c + 32 for c in range(65, 91)}
_RAW_TEXT = {name: re.compile(rf"</{name}\s*>") for name in ("script", "style")}
_LANGUAGE = re.compile(r"\blang\s*=\s*[\"']?\s*([a-z]{2,3})\b")


def _starts(lowered: str, at: int, name: str) -> bool:
    """Whether a tag or element of this name begins at ``at``."""
    end = at + len(name)
    return lowered.startswith(name, at) and not (lowered[end : end + 1].isalnum() or lowered[end : end + 1] == "_")


def visible_text(page: str | None) -> str:
    """What a reader sees: no scripts, styles, comments or tags; character references resolved.

    One walk from tag to tag; an end that was once sought in vain is not sought again, so broken
    pages take no longer.  What is never closed is a tag, and a ``<`` without any ``>`` is text.
    """
    if not page:
        return ""
    lowered, out, at, unclosed = page.translate(_ASCII_LOWER), [], 0, set()
    while (i := page.find("<", at)) >= 0:
        out.append(page[at:i])
        stop = -1
        if "!" not in unclosed and page.startswith("<!--", i):
            stop = page.find("-->", i + 4)
            stop = stop + 3 if stop >= 0 else unclosed.add("!") or -1
        else:
            for name, close in _RAW_TEXT.items():
                if name not in unclosed and _starts(lowered, i + 1, name):
                    m = close.search(lowered, i)
                    stop = m.end() if m else unclosed.add(name) or -1
        if stop < 0:
            stop = page.find(">", i) + 1
            if not stop:
                out[-1] += page[i:]
                at = len(page)
                break
        at = stop
    out.append(page[at:])
    return html.unescape(" ".join(out))


def declared_language(page: str | None) -> str | None:
    """The ``lang`` of the first ``html`` tag that has one."""
    lowered, at = page.translate(_ASCII_LOWER) if page else "", 0
    while (i := lowered.find("<html", at)) >= 0:
        at = i + 5
        if _starts(lowered, i, "<html"):
            stop = lowered.find(">", i)
            at = len(lowered) if stop < 0 else stop
            if m := _LANGUAGE.search(lowered, i, at):
                return m.group(1)
    return None


def _trigrams(column: pa.Array) -> Iterator[np.ndarray]:
    """Per text, the slots of all its trigrams of characters (A-Z lower-cased)."""
    for c in K.chunks(column, lower=True):
        places, first = c.characters()
        slots = (c.character_gram_hashes(3, places) >> np.uint64(64 - BITS)).astype(np.int64)
        for i in range(c.n):
            yield slots[first[i] : max(first[i], first[i + 1] - 2)]


class Model:
    def __init__(self, languages: list[str], counts: np.ndarray):
        self.languages = languages
        share = (counts + 0.05) / (counts + 0.05).sum(axis=1, keepdims=True)
        self.logs = np.log(share).T.astype(np.float32)  # (slots, languages)

    def evidence(self, slots: np.ndarray) -> np.ndarray:
        """Log-likelihoods up to a constant, of the weight of the independent trigrams among ``slots``."""
        if not len(slots):
            return np.zeros(len(self.languages))
        found, times = np.unique(slots, return_counts=True)
        mean = times @ self.logs[found].astype(np.float64) / len(slots)
        return (mean - mean.max()) * len(slots) / (1 + len(slots) / EFFECTIVE)


def train(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", most: int = MAX_SAMPLE) -> Model | None:
    known = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.lower(F.col(lang_col)).alias("lang")).dropna()
    # one row per language
    sizes = {r["lang"]: r["count"] for r in known.groupBy("lang").count().orderBy("lang").limit(MAX_LANGUAGES + 1).collect()}
    languages = sorted(sizes)
    if not languages:
        return None
    if len(languages) > MAX_LANGUAGES:
        raise ValueError(f"over {MAX_LANGUAGES} languages")
    # of each language the ids whose hash is below a share of all hashes: about ``most``, whatever its size
    share = spark_table(docs, [(lang, min((1 << 63) - 1, -(1 << 63) + int((1 << 64) * min(1.0, most / n)))) for lang, n in sizes.items()])
    sample = known.withColumn("h", F.xxhash64("id")).join(F.broadcast(share), "lang").filter("h <= least").dropDuplicates(["id"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = {lang: k for k, lang in enumerate(languages)}
        table: dict[int, np.ndarray] = {}
        for batch in batches:
            for lang, slots in zip(batch.column("lang").to_pylist(), _trigrams(batch.column("text")), strict=True):
                own = table.setdefault(place[lang], np.zeros(1 << BITS, np.int32))
                np.add.at(own, slots, 1)
        for k, own in table.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([own.tobytes()], pa.binary())], ["k", "counts"])

    counts = np.zeros((len(languages), 1 << BITS), np.float32)
    for row in sample.select("lang", "text").coalesce(8).mapInArrow(count, "k int, counts binary").toLocalIterator():
        counts[row["k"]] += np.frombuffer(row["counts"], np.int32)
    return Model(languages, counts)


def spark_table(docs: DataFrame, rows: list[tuple[str, int]]) -> DataFrame:
    return docs.sparkSession.createDataFrame(rows, "lang string, least long")


def _softmax(scores: Column) -> Column:
    top = F.transform(scores, lambda x: F.exp(x - F.array_max(scores)))
    total = F.aggregate(top, F.lit(0.0), lambda a, x: a + x)
    return F.transform(top, lambda x: x / total)


def identify(pages: DataFrame, model: Model | None, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page row: id, lang, probability, text_lang, declared, host, host_pages."""
    id_type = pages.schema[id_col].dataType.simpleString()
    if model is None:
        host, _ = host_and_path(url_col)
        return pages.select(F.col(id_col), F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("probability"), F.lit(None).cast("string").alias("text_lang"), F.lit(None).cast("string").alias("declared"), host.alias("host"), F.lit(0).cast("long").alias("host_pages"))
    spark, names = pages.sparkSession, model.languages
    shared = spark.sparkContext.broadcast(model)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                raw = part.column("html").to_pylist()
                seen = pa.array([visible_text(x) for x in raw], pa.large_string())
                logs = [m.evidence(s).tolist() for s in _trigrams(seen)]
                said = [d if d in m.languages else ("other" if d else "none") for d in map(declared_language, raw)]
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("host"), pa.array(said, pa.string()), pa.array(logs, pa.list_(pa.float64()))], ["id", "host", "declared", "text"])

    host, _ = host_and_path(url_col)
    base = pages.select(F.col(id_col).alias("id"), host.alias("host"), F.col(html_col).alias("html"))
    own = base.mapInArrow(read, f"id {id_type}, host string, declared string, text array<double>").withColumn("post", _softmax(F.col("text")))
    own = materialise(own, "language-pages")

    sums = [F.sum(F.col("post")[k]).alias(f"s{k}") for k in range(len(names))]
    add = [F.sum(f"s{k}").alias(f"s{k}") for k in range(len(names))]
    labels = F.split("host", r"\.")
    last = lambda n: F.array_join(F.slice(labels, F.greatest(F.lit(1), F.size(labels) - n + 1), n), ".")
    hosts = own.groupBy("host").agg(F.count(F.lit(1)).alias("n"), *sums)
    hosts = materialise(hosts.withColumns({f"level{n}": last(n) for n in LEVELS}), "language-hosts")
    whole = hosts.agg(F.sum("n").alias("n"), *add).first()
    total = float(whole["n"] or 0)
    base_prior = [((whole[f"s{k}"] or 0.0) + 1) / (total + len(names)) for k in range(len(names))]

    def smooth(own_sums: list[Column], n: Column, parent: list[Column]) -> list[Column]:
        return [(s + SMOOTH * p) / (n + SMOOTH) for s, p in zip(own_sums, parent, strict=True)]

    cols, parent, prior = [F.col(f"s{k}") for k in range(len(names))], [F.lit(x) for x in base_prior], None
    for i, n in enumerate(LEVELS):
        above = [f"level{m}" for m in LEVELS[:i]]
        own_level = hosts.groupBy(f"level{n}", *above).agg(F.sum("n").alias("n"), *add)
        if prior is not None:
            own_level, parent = own_level.join(prior, above[-1]), [F.col(f"p{k}") for k in range(len(names))]
        prior = own_level.select(f"level{n}", *[p.alias(f"p{k}") for k, p in enumerate(smooth(cols, F.col("n"), parent))])
    host_table = hosts.join(prior, f"level{LEVELS[-1]}").select("host", F.col("n").alias("host_pages"), F.array(*cols).alias("host_sums"), F.array(*[F.col(f"p{k}") for k in range(len(names))]).alias("domain_prior"))

    # at most (languages + 2) rows
    said = {r["declared"]: [r[f"s{k}"] for k in range(len(names))] for r in own.groupBy("declared").agg(*sums).collect()}
    every = [sum(v[k] for v in said.values()) for k in range(len(names))]
    trust = F.array(*[F.lit(0.0)] * len(names))
    for d, v in said.items():
        trust = F.when(F.col("declared") == d, F.array(*[F.lit(float(np.log((v[k] + 1) / (every[k] + len(names) + 2)))) for k in range(len(names))])).otherwise(trust)

    joined = salted_join(own, host_table, ["host"], "host_pages", int(total))
    prior = F.transform(F.arrays_zip("host_sums", "post", "domain_prior"), lambda x: F.log((F.greatest(F.lit(0.0), x["host_sums"] - x["post"]) + SMOOTH * x["domain_prior"]) / (F.col("host_pages") - 1 + SMOOTH)))
    fused = F.transform(F.arrays_zip(F.col("text").alias("t"), trust.alias("d"), prior.alias("h")), lambda x: x["t"] + x["d"] + x["h"])
    known = F.array(*[F.lit(x) for x in names])
    out = joined.withColumn("_p", _softmax(fused)).withColumn("_best", F.array_max("_p"))
    return out.select(
        F.col("id").alias(id_col),
        F.element_at(known, F.array_position("_p", F.col("_best")).cast("int")).alias("lang"),
        F.col("_best").alias("probability"),
        F.element_at(known, F.array_position("post", F.array_max("post")).cast("int")).alias("text_lang"),
        "declared",
        "host",
        "host_pages",
    )
