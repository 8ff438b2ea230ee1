"""Every operator on nulls in any column, repeated rows, a very long text, clashing column names and empty tables."""

from __future__ import annotations

import public_tokenizers
import pytest
from pyspark.sql import functions as F

from foretell.llm import decontaminate, jaccard_join, language, line_dedup, mixing, quality, sharding, token_counts, toxicity, url_filter

LONG = "word other more " * 120_000  # 1.9 million characters in one line
CLASHES = ["id", "node", "hub", "size", "shard", "slot", "n", "line", "key", "host", "path", "block", "hash", "kept", "probability", "_row", "_id", "_text", "_no", "_block", "_shard", "sid", "gid", "component", "label"]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(1, "a short text of a few words only", "en", "s1"), (2, None, None, None), (None, "no identifier here at all", "fr", "s1"), (3, "", "en", "s2"), (4, LONG, "en", "s2"), (5, "copy of words that stand twice in the table", "de", "s1"), (6, "copy of words that stand twice in the table", "de", None), (1, "a short text of a few words only", "en", "s1")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    return df.select("*", *[F.lit(f"clash {c}").alias(c) for c in CLASHES]).repartition(3)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (3, 0, 1), (4, 1, 0), (5, 0, 1), (6, 1, None), (None, 1, 1), (99, 1, 0)], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def pages(spark):
    rows = [(1, "https://www.Example.com/en/x?q", "<html lang=en><p>words that are seen</p>"), (2, None, None), (None, "ftp://x.net/es/", "<p>"), (3, "no address", LONG), (3, "no address", LONG), (4, "http://", "<script>" * 50_000)]
    return spark.createDataFrame(rows, "page_id long, url string, html string").select("*", *[F.lit("x").alias(c) for c in ("id", "host", "path", "lang", "text", "declared", "n", "rule")])


def run(name, docs, labels, pages, spark):
    if name == "shards":
        return sharding.shard_documents(docs, 3)
    if name == "quality":
        return quality.judge(docs, quality.train(docs, labels))
    if name == "toxicity":
        return toxicity.score(docs, toxicity.train(docs, toxicity.with_complement(labels), ["low_quality", "toxic"]), ["low_quality", "toxic"])
    if name == "decontaminate":
        return decontaminate.scan(docs, spark.createDataFrame([(1, "words that stand twice"), (None, "few words only"), (2, None)], "item_id long, text string"))
    if name == "lines":
        return line_dedup.repeated_lines(docs)
    if name == "mix":
        return mixing.mix(docs)
    if name == "tokens":
        return token_counts.count_tokens(docs, public_tokenizers.path("word_bpe_49k.json"))
    if name == "jaccard":
        return jaccard_join.link(docs)
    if name == "urls":
        return url_filter.judge_urls(pages, [("com", "/", "allow"), ("net", "/es/", "block")])
    return language.identify(pages, language.train(docs))


NAMES = ["shards", "quality", "toxicity", "decontaminate", "lines", "mix", "tokens", "jaccard", "urls", "language"]


@pytest.mark.parametrize("name", NAMES)
def test_odd_rows_and_clashing_names(spark, docs, labels, pages, name):
    out = run(name, docs, labels, pages, spark).collect()
    assert len(out) == (6 if name in ("urls", "language") else 8)


@pytest.mark.parametrize("name", NAMES)
def test_empty_tables(spark, docs, labels, pages, name):
    none = lambda df: df.filter("false")
    assert run(name, none(docs), none(labels), none(pages), spark).count() == 0


def test_filters_keep_columns(spark, docs, labels):
    item = spark.createDataFrame([(1, "words that stand twice")], "item_id long, text string")
    for out in (toxicity.without_toxic(docs, None), decontaminate.clean_documents(docs, item), jaccard_join.one_of_each(docs), mixing.mixed_documents(docs), line_dedup.without_repeated(docs)):
        assert out.columns == docs.columns and out.count() > 0
        assert {r["hub"] for r in out.select("hub").collect()} == {"clash hub"}
