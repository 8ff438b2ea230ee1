"""Operators against brute force on small fixtures with nulls, empty and repeated rows."""

from __future__ import annotations

import random
import re
import string
import tracemalloc
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from foretell.llm import decontaminate, jaccard_join, language, mixing, quality, sharding, token_counts, toxicity, url_filter
from foretell.llm import components as components_module
from foretell.llm import textkernel as K
from foretell.llm.components import components

LOWER = {ord(c): c.lower() for c in string.ascii_uppercase}
SPACE = r"[^\x20\x09-\x0D]+"
ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def frame(spark, rows, schema="doc_id long, text string"):
    return spark.createDataFrame(rows, schema).repartition(3)


def words(rng, n, vocabulary=40):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


def shingles(text, n):
    w = re.findall(SPACE, (text or "").translate(LOWER))
    return frozenset(tuple(w[i : i + n]) for i in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)] if w else [])


def family(rng, size, edits):
    base = [f"b{rng.randrange(10**6)}" for _ in range(120)]
    out = []
    for _ in range(size):
        t = list(base)
        for _ in range(rng.randint(0, edits)):
            t[rng.randrange(len(t))] = rng.choice(["edit", "other", f"x{rng.randrange(10**6)}"])
        out.append(" ".join(t))
    return out


def test_jaccard_components_against_brute_force(spark):
    rng = random.Random(2)
    texts = [*family(rng, 60, 5), *family(rng, 25, 3), *(words(rng, rng.randint(1, 60), 10**6) for _ in range(40))]
    shared = " ".join(f"p{i}" for i in range(60))
    texts += [words(rng, 80, 10**6) + " " + shared for _ in range(30)]
    texts += [texts[0]] * 20 + [None, "", "  \n", "a b", "A  B", "a b c", "a b c"]
    rows = list(enumerate(texts)) + [(3, texts[3])]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.link(frame(spark, rows)).collect()}
    sets = {i: shingles(t, 4) for i, t in enumerate(texts)}
    parent = {i: i for i in sets}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in sets:
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    assert got == {i: (len(s), find(i)) for i, s in sets.items()}
    kept = jaccard_join.one_of_each(frame(spark, rows), n=4, num=85, den=100).collect()
    assert sorted(r["doc_id"] for r in kept) == sorted(i for i, s in sets.items() if not s or find(i) == i)
    assert jaccard_join.link(frame(spark, rows).filter("false")).count() == 0


def test_components(spark):
    links = [(i, i + 1) for i in range(0, 30)] + [(100, 200), (200, 300), (7, 7), (300, 100)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(31)}, 100: 100, 200: 100, 300: 100}


def test_decontamination_against_brute_force(spark):
    rng = random.Random(4)
    items = [(i, words(rng, rng.choice([3, 10, 14, 25]))) for i in range(12)] + [(50, None), (51, "..."), (52, "Ünï one")]
    docs = []
    for d in range(40):
        parts = [words(rng, 20)]
        if d % 3 == 0:
            w = items[d % 12][1].split()
            a = rng.randrange(max(1, len(w) - 10))
            parts.append(", ".join(w[a : a + 12]).upper())
        docs.append((d, " -- ".join([*parts, words(rng, 5)])))
    docs += [(90, None), (91, ""), (92, "ünï ONE. Ünï one"), (0, docs[0][1])]
    spans = {}
    for max_words in (10**6, 40):
        out = decontaminate.scan(frame(spark, docs), spark.createDataFrame(items, "item_id long, text string"), max_words=max_words).collect()
        assert len(out) == len(docs)
        for r in out:
            text = dict(docs)[r["doc_id"]]
            w = re.findall(ALNUM, (text or "").translate(LOWER))
            hit, found = set(), set()
            for item, t in items:
                v = re.findall(ALNUM, (t or "").translate(LOWER))
                size = min(10, len(v))
                for a in range(len(v) - size + 1 if size else 0):
                    for i in range(len(w) - size + 1):
                        if w[i : i + size] == v[a : a + size]:
                            hit |= set(range(i, i + size))
                            found.add(str(item))
            assert (r["n_words"], r["n_hit"], r["items"]) == (len(w), len(hit), sorted(found)), r["doc_id"]
            spans[r["doc_id"]] = [(s["start"], s["stop"]) for s in r["spans"]]
    assert [dict(docs)[92].encode()[a:b].decode() for a, b in spans[92]] == ["Ünï one"]
    clean = decontaminate.clean_documents(frame(spark, docs), spark.createDataFrame(items, "item_id long, text string"))
    assert 92 not in {r["doc_id"] for r in clean.collect()} and clean.columns == ["doc_id", "text"]
    assert decontaminate.scan(frame(spark, docs), spark.createDataFrame([], "item_id long, text string")).filter("n_hit > 0").count() == 0


def test_decontamination_of_repeating_and_common_passages_against_brute_force(spark):
    rng = random.Random(14)
    shared = words(rng, 9)
    items = [(i, f"{shared} {words(rng, 6)} {shared}") for i in range(6)] + [(7, "a " * 30), (8, "a b " * 12), (9, " ".join("ab"[k % 3 == 0] for k in range(40))), (10, "one two three four"), (11, words(rng, 9))]
    docs = [(d, " ".join(rng.choice([shared, "a " * rng.randint(3, 15), "a b " * rng.randint(2, 8), items[rng.randrange(11)][1], "one two three four", words(rng, 4)]) for _ in range(4))) for d in range(40)]
    docs.append((99, ("b a a " * 20000) + shared))
    out = {r["doc_id"]: (r["n_hit"], r["items"]) for r in decontaminate.scan(frame(spark, docs), spark.createDataFrame(items, "item_id long, text string")).collect()}
    windows = {}
    for item, t in items:
        v = t.split()
        for a in range(len(v) - min(10, len(v)) + 1):
            windows.setdefault(tuple(v[a : a + min(10, len(v))]), set()).add(str(item))
    for d, t in docs:
        w, hit, found = t.split(), set(), set()
        for size in {len(k) for k in windows}:
            for i in range(len(w) - size + 1):
                who = windows.get(tuple(w[i : i + size]))
                if who:
                    hit |= set(range(i, i + size))
                    found |= who
        assert out[d] == (len(hit), sorted(found)), d


def test_token_counts_equal_the_library(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    texts = ["", "Hello, World!  it's I'LL", "naïve café ÀÉ ΑΣ ς İstanbul ß", "<|endoftext|>x <|startoftext|><|endoftext|", "12345 ½ ²\t\n x y", "日本語のテキスト 😀👍🏽 é", "#$%^ ''s 's''t", "a" * 3000, "\x1c\x1d z", "don't DON'T we'Ve"]
    rng = random.Random(1)
    texts += ["".join(rng.choice("aAbé '1<|>😀́ st") for _ in range(60)) for _ in range(60)]
    got = {r["doc_id"]: (r["n_bytes"], r["n_tokens"]) for r in token_counts.count_tokens(frame(spark, [*enumerate(texts), (999, None)]), path).collect()}
    for i, t in enumerate(texts):
        assert got[i] == (len(t.encode()), len(library.encode(t, add_special_tokens=False).ids)), repr(t)
    assert got[999] == (0, 0)


def test_long_texts_are_cut_between_words():
    spec = {"merges": [("a", "b")], "suffix": "", "pattern": r"[a-z]+", "special": []}
    m = token_counts.Merger(spec)
    text = "ab " * 1000
    old, token_counts.PIECE_CHARS = token_counts.PIECE_CHARS, 7
    try:
        assert m.count(text) == 1000
    finally:
        token_counts.PIECE_CHARS = old


def test_url_rules(spark):
    rules = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block")]
    cases = {
        "http://Example.COM/en/x?q": ("example.com", "/en/x", "example.com/en/", "block"),
        "https://www.example.com/en/": ("www.example.com", "/en/", "www.example.com/en/", "allow"),
        "http://a.b.net/es/1#f": ("a.b.net", "/es/1", "net/es/", "block"),
        "http://myexample.com/en/": ("myexample.com", "/en/", "com/", "allow"),
        "http://x.com": ("x.com", "", None, "allow"),
        "no scheme.com/en/": ("", "", None, "allow"),
        "http://example.com?a/en/": ("example.com", "", None, "allow"),
        "": ("", "", None, "allow"),
    }
    rows = [(i, u) for i, u in enumerate(cases)] + [(99, None)]
    got = {r["page_id"]: tuple(r)[1:] for r in url_filter.judge_urls(frame(spark, rows, "page_id long, url string"), rules).collect()}
    assert got == {**{i: v for i, v in enumerate(cases.values())}, 99: ("", "", None, "allow")}
    with pytest.raises(ValueError):
        url_filter.build_index([("a", "/", "allow"), ("a", "/", "block")])


def test_url_index_confirms_strings(tmp_path):
    path = tmp_path / "index"
    path.write_bytes(url_filter.build_index([("a.com", "/x", "block")]))
    index = url_filter.Index(str(path))
    digest = int(index.digests[0])
    assert index.confirm(0, digest, b"a.com\n/x") == 0 and index.confirm(0, digest, b"b.com\n/x") == -1


def test_quality_statistics_against_brute_force(spark):
    rng = random.Random(6)
    texts = ["", "a a a a", "x\n\nx\n x\nx\t", "é ü|<>#*$%& ÿ", *("\n".join(words(rng, rng.randint(0, 9), 5) for _ in range(6)) for _ in range(40))]

    def brute(text):
        w = re.findall(SPACE, text)
        g = Counter(zip(w, w[1:], w[2:], strict=False))
        rep = {k for i in range(len(w) - 2) if g[tuple(w[i : i + 3])] > 1 for k in (i, i + 1, i + 2)}
        seen, dup = set(), 0
        for line in text.split("\n"):
            if re.search(SPACE, line):
                dup += line in seen
                seen.add(line)
        return [len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(rep)]

    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    for size in (1, 100, 10**6):
        old, K.CHUNK_BYTES = K.CHUNK_BYTES, size
        try:
            cols = [quality.statistics(c) for c in K.chunks(pa.array([*texts, None]))]
        finally:
            K.CHUNK_BYTES = old
        got = np.stack([np.concatenate([c[n] for c in cols]) for n in names], axis=1).tolist()
        assert got == [brute(t) for t in [*texts, ""]]


def test_quality_and_toxicity_held_out(spark):
    rng = random.Random(8)
    rows, labels = [], []
    for d in range(400):
        bad, rude = d % 4 == 0, d % 5 == 0
        t = [f"w{rng.randrange(300)}" + ("###" if bad else "") for _ in range(80)]
        if rude:
            t[rng.randrange(80)] = rng.choice(["villain", "scoundrel"])
        rows.append((d, " ".join(t)))
        if d < 300:
            labels.append((d, int(not bad), int(rude)))
    docs, lab = frame(spark, [*rows, (900, None)]), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    kept = {r["doc_id"]: r["kept"] for r in quality.judge(docs, quality.train(docs, lab)).collect()}
    assert np.mean([kept[d] == (d % 4 > 0) for d in range(300, 400)]) > 0.95 and kept[900] is False
    chain = toxicity.train(docs, toxicity.with_complement(lab), ["low_quality", "toxic"])
    p = {r["doc_id"]: r["p_toxic"] for r in toxicity.score(docs, chain, ["low_quality", "toxic"]).collect()}
    assert np.mean([(p[d] >= 0.5) == (d % 5 == 0) for d in range(300, 400)]) > 0.95 and p[900] < 0.5
    assert {r["doc_id"] for r in toxicity.without_toxic(docs, chain).collect()} == {d for d, v in p.items() if v < 0.5}
    assert quality.train(docs, lab.filter("false")) is None and toxicity.train(docs, toxicity.with_complement(lab.filter("false")), ["toxic"]) is None


def test_mixing_targets_and_exactness(spark):
    assert mixing.targets([100, 100, 100], [5, 2, 1], 3) == pytest.approx([187.5, 75.0, 37.5])
    assert mixing.targets([10, 500, 500], [5, 2, 1], 3) == pytest.approx([30, 980 * 2 / 3, 980 / 3])
    assert mixing.targets([], [], 3) == [] and mixing.targets([0, 0], [5, 2], 3) == [0, 0]
    q = mixing.splitting_tree([100, 7, 0], 8, 1)
    assert q.sum(axis=1).tolist() == [100, 7, 0] and np.ptp(q.sum(axis=0)) <= 1
    rng = random.Random(9)
    rows = [(i, None if i % 17 == 0 else words(rng, rng.randint(0, 30)), ["a", "b", "c", None][min(3, rng.randrange(6))]) for i in range(400)]
    rows += rows[:5]
    docs = frame(spark, rows, "doc_id long, text string, source string")
    out = mixing.mix(docs).collect()
    assert len(out) == len(rows)
    by = {}
    for r in out:
        t = by.setdefault(r["source"], [r["target"], 0, 0, r["source_size"]])
        t[1] += r["taken"]
        t[2] += r["size"]
        assert r["taken"] <= 3 * r["size"] and len(r["shards"]) == r["copies"] and all(0 <= s < 8 for s in r["shards"])
    for target, taken, size, whole in by.values():
        assert size == whole and abs(taken - target) <= 3
    assert sorted(map(str, mixing.mix(docs.repartition(5)).collect())) == sorted(map(str, out))
    drawn = mixing.mixed_documents(docs)
    assert drawn.columns == docs.columns and abs(drawn.count() - sum(r["copies"] for r in out)) <= 4
    assert mixing.mix(docs.filter("false")).count() == 0 and mixing.mixed_documents(docs.filter("false")).count() == 0


def test_mixing_against_one_walk_over_the_blocks(spark, monkeypatch):
    """The words taken and the shards of all copies, found by walking each source's rounds in order."""
    monkeypatch.setattr(mixing, "PART_ROWS", 50)
    rng = random.Random(10)
    rows = [(i, words(rng, rng.randint(0, 25)), rng.choice("aaaaaabbc"), i) for i in range(300)]
    docs = frame(spark, rows, "doc_id long, text string, source string, size long")
    got = {r["doc_id"]: r for r in mixing.mix(docs, n_shards=4).collect()}
    hashed = docs.select("doc_id", "source", mixing._document_hash("doc_id", "text", 20).alias("h"), F.size(F.split("text", " ")).alias("n"), F.col("text")).collect()
    placed = Counter()
    for no, source in enumerate("abc"):
        own = [(r["h"], r["doc_id"], len(r["text"].split())) for r in hashed if r["source"] == source]
        total, blocks = sum(n for *_, n in own), min(64, len(own))
        whole = sum(len(r["text"].split()) for r in hashed)
        target = mixing.targets([sum(len(r["text"].split()) for r in hashed if r["source"] == s) for s in "abc"], [5, 2, 1], 3)[no]
        assert whole and got[own[0][1]]["target"] == pytest.approx(target)
        rounds = int(target // total) if total else 0
        order = spark.range(blocks).selectExpr("cast(id as int) as block", *[f"xxhash64(20, {no}, cast(id as int), {e}) as o{e}" for e in range(4)]).collect()
        taken = {d: rounds * n for _, d, n in own}
        left = round(target - rounds * total) if rounds < 3 else 0
        for b in sorted(order, key=lambda r: (r[f"o{rounds}"], r["block"])):
            for h, d, n in sorted((h, d, n) for h, d, n in own if h % blocks == b["block"]):
                use = min(n, left)
                taken[d] += use
                left -= use
        assert all(got[d]["taken"] == taken[d] for _, d, _ in own)
        for d in (d for _, d, _ in own):
            placed.update(got[d]["shards"])
    assert max(placed.values()) - min(placed.values()) <= 0.5 * max(placed.values())
    drawn = mixing.mixed_documents(docs, n_shards=4)
    parts = drawn.rdd.getNumPartitions() // 4
    assert parts > 1 and drawn.columns == docs.columns
    seen = Counter((r["doc_id"], r["p"] // parts) for r in drawn.select("doc_id", F.spark_partition_id().alias("p")).collect())
    wanted = Counter((d, s) for d, r in got.items() for s in r["shards"])
    edges = sum((wanted - seen).values()) + sum((seen - wanted).values())
    assert edges <= 3  # an edge document of which no word was left


def test_sharding_is_even_and_keeps_copies_together(spark):
    rows = [(i, f"text {i}") for i in range(300)] + [(1000 + i, f"copy {i % 20}") for i in range(100)] + [(2000 + i, "hot") for i in range(180)] + [(5000, None), (5001, None), (5002, ""), (7, "text 7")]
    out = sharding.shard_documents(frame(spark, rows)).collect()
    texts = {d: t for d, t in rows}
    count, slots, groups = Counter(r["shard"] for r in out), {}, {}
    for r in out:
        t = texts[r["doc_id"]]
        assert r["size"] == len((t or "").encode()) + 1 and r["text_crc32"] == zlib.crc32((t or "").encode())
        slots.setdefault(r["shard"], []).append(r["slot"])
        if t is not None:
            groups.setdefault(t, set()).add(r["shard"])
    assert len(out) == len(rows) and max(count.values()) - min(count.values()) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert sum(len(groups[f"copy {i}"]) > 1 for i in range(20)) <= 2 and len(groups["hot"]) <= 4
    assert sharding.shard_documents(frame(spark, rows).filter("false")).count() == 0
    cut = sharding.cut_links(sharding.shard_documents(frame(spark, rows))).first()
    assert cut["cut_pairs"] < 0.8 * cut["pairs"]


def test_sharding_keeps_copies_of_one_id_and_of_no_id_together(spark):
    rows = [(i % 150, f"text {i % 150}") for i in range(300)] + [(None, f"nameless {i % 40}") for i in range(80)] + [(1000 + i % 20, f"part {i}") for i in range(40)] + [(3000 + i, f"single {i}") for i in range(60)]
    out = sharding.shard_documents(frame(spark, rows)).collect()
    count, groups = Counter(r["shard"] for r in out), {}
    for r in out:
        groups.setdefault(r["doc_id"] if r["doc_id"] is not None else r["text_crc32"], []).append(r["shard"])
    assert len(out) == len(rows) and max(count.values()) - min(count.values()) <= 1
    pairs = [g for g in groups.values() if len(g) == 2]
    assert len(pairs) == 210 and sum(len(set(g)) > 1 for g in pairs) <= 10


def test_sharding_by_given_links(spark):
    rows = [(i, f"text {i}") for i in range(200)] + [(i, f"other {i}") for i in range(40)] + [(None, "x")]
    links = spark.createDataFrame([(i, f"h{i % 50}") for i in range(100)] + [(None, "h1"), (7, None)], "id long, hub string")
    out = sharding.shard_documents(frame(spark, rows), 4, links=links).collect()
    count, groups = Counter(r["shard"] for r in out), {}
    for r in out:
        if r["doc_id"] is not None and r["doc_id"] < 100:
            groups.setdefault(r["doc_id"] % 50, set()).add(r["shard"])
    assert len(out) == len(rows) and max(count.values()) - min(count.values()) <= 1
    assert sum(len(g) > 1 for g in groups.values()) <= 4


def test_language_fusion(spark):
    rng = random.Random(3)
    sounds = {"xx": ["ba", "bo", "bu"], "yy": ["ki", "ke", "ku"]}
    speak = lambda lang, n: " ".join("".join(rng.choice(sounds[lang]) for _ in range(3)) for _ in range(n))
    docs = spark.createDataFrame([(i, speak(lang, 30), lang) for i, lang in enumerate(["xx", "yy"] * 30)], "doc_id long, text string, lang string")
    pages = []
    for i in range(80):
        lang = "xx" if i % 2 else "yy"
        host = "x.site" if lang == "xx" else "y.site"
        pages.append((i, f"http://{host}/{i}", f"<html lang='{lang}'><script>{speak('yy', 9)}</script><p>{speak(lang, 20)}</p></html>"))
    pages += [(200, "http://x.site/z", None), (201, "http://y.site/z", "<p></p>"), (202, None, None), (203, "http://x.site/q", f"<html lang='yy'><p>{speak('xx', 25)}")]
    got = {r["page_id"]: r for r in language.identify(spark.createDataFrame(pages, "page_id long, url string, html string"), language.train(docs)).collect()}
    assert all(got[i]["lang"] == ("xx" if i % 2 else "yy") for i in range(80))
    assert got[200]["lang"] == "xx" and got[201]["lang"] == "yy" and got[203]["lang"] == "xx" and got[202]["host"] == ""
    assert all(0 < r["probability"] <= 1.0 + 1e-9 for r in got.values())
    assert language.visible_text("a<!-- x --><style>b</style>&eacute;<b>c</b>").split() == ["a", "é", "c"]
    assert language.identify(spark.createDataFrame(pages, "page_id long, url string, html string"), None).filter("lang is not null").count() == 0


def test_pages_are_read_in_linear_time_and_as_the_patterns_say():
    import html as entities
    import time

    hidden = re.compile(r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>")
    declared = re.compile(r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?\s*([a-z]{2,3})\b")
    rng = random.Random(6)
    bits = ["<script>", "</script >", "<SCRIPT x>", "<style>", "</style>", "<!--", "-->", "<b>", "</b", ">", "<", "text", "é", " ", "<html lang='DE'>", "<html", " lang = en", "<scripty>", "</scriptx>", "&eacute;"]
    for _ in range(3000):
        page = "".join(rng.choice(bits) for _ in range(rng.randint(0, 12)))
        assert language.visible_text(page).split() == entities.unescape(hidden.sub(" ", page)).split(), page
        m = declared.search(page)
        assert language.declared_language(page) == (m.group(1).lower() if m else None), page
    for bit in bits:
        began = time.time()
        language.visible_text(bit * 100_000)
        language.declared_language(bit * 100_000)
        assert time.time() - began < 5, bit


def test_every_language_with_documents_is_found(spark):
    rng = random.Random(8)
    names = [f"{a}{b}" for a in "abcdefghij" for b in "klmnopq"]
    say = lambda k: " ".join(chr(0x4E00 + 5 * k + rng.randrange(5)) + chr(0x4E00 + 5 * k + rng.randrange(5)) for _ in range(30))
    docs = spark.createDataFrame([(i, say(i % 70), names[i % 70]) for i in range(140)] + [(1000 + i, say(0), names[0]) for i in range(500)], "doc_id long, text string, lang string")
    pages = spark.createDataFrame([(k, f"http://h{k}.site/", f"<p>{say(k)}</p>") for k in range(70)], "page_id long, url string, html string")
    assert {r["page_id"]: r["lang"] for r in language.identify(pages, language.train(docs, most=50)).collect()} == dict(enumerate(names))


def test_pipeline_stages_keep_columns(spark, small):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{small}/documents.parquet")
    before = docs
    for name, stage in P.STAGES[:-1]:
        after = stage(spark, before, small)
        assert after.columns == docs.columns, name
        before = after
        if name == "near_duplicates":
            break
    out = P.run(spark, small)
    assert {"doc_id", "shard", "slot"} <= set(out.columns) and out.count() > 100


def test_chain_is_fitted_in_little_memory():
    """The driver holds 4 bytes a feature number of the sample, not several 8-byte copies."""
    rng = np.random.default_rng(3)
    toxic = (rng.random(6000) < 0.2).astype(np.float64)
    ids = [np.unique(np.concatenate((rng.zipf(1.15, 600) * 7919 % (1 << 20), rng.integers(500, 530, 3 * int(t))))).astype(np.int32) for t in toxic]
    tracemalloc.start()
    chain = toxicity.fit_chain(toxicity.Presence(ids), [toxic], ["toxic"])
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert set(chain.links[0][0]) == set(range(500, 530)) and peak < 100e6
    assert toxicity.fit_chain(toxicity.Presence([]), [np.zeros(0)], ["toxic"]) is None


def test_a_round_of_components(spark):
    links = spark.createDataFrame([(i + 1, i) for i in range(9)], "a long, b long")
    plan = components_module._small_star(components_module._large_star(links))._jdf.queryExecution().optimizedPlan().toString()
    # the large star's rows are not made distinct, and the small star has no second branch
    assert plan.count("Aggregate") == 4
    got = {tuple(r) for r in components_module._small_star(components_module._large_star(links)).collect()}
    both = [(a, b) for i in range(9) for a, b in ((i + 1, i), (i, i + 1))]
    low = {a: min([a, *(y for x, y in both if x == a)]) for a, _ in both}
    large = {(b, low[a]) for a, b in both if b > a and b != low[a]}
    least = {a: min(y for x, y in large if x == a) for a, _ in large}
    assert got == {(b, least[a]) for a, b in large if b != least[a]} | set(least.items())


def test_pipeline_hands_few_texts_at_a_time(spark):
    import corpus_pipeline as P

    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    try:
        for given, held in ((10000, P.BATCH_ROWS), (0, P.BATCH_ROWS), (-1, P.BATCH_ROWS), (7, 7)):
            spark.conf.set(name, str(given))
            P.small_batches(spark)
            assert int(spark.conf.get(name)) == held
    finally:
        spark.conf.set(name, before)
