from __future__ import annotations

import random

from pyspark.sql import functions as F

from foretell.llm import line_dedup as L


def distance(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def edited(rng: random.Random, text: str, edits: int) -> str:
    out = list(text)
    for _ in range(edits):
        at, kind = rng.randrange(len(out)), rng.random()
        if kind < 0.34:
            out[at] = rng.choice("abcé😀")
        elif kind < 0.67:
            out.insert(at, rng.choice("abcé😀"))
        elif len(out) > 1:
            del out[at]
    return "".join(out)


def test_banded_distance_with_and_without_trimming(spark):
    rng = random.Random(3)
    rows = []
    for _ in range(250):
        a = "".join(rng.choice("abcé😀") for _ in range(rng.randint(1, 14)))
        rows.append((a, edited(rng, a, rng.randint(0, 4))))
    rows += [("", ""), ("a", ""), ("", "b"), ("ab", "ab")]
    df = spark.createDataFrame(rows, "x string, y string").withColumn("a", F.col("x")).withColumn("b", F.col("y"))
    for edits in (1, 2, 3):
        cut = L.trimmed(df).withColumn("d", L.banded_distance(F.col("x"), F.col("y"), edits))
        for r in cut.collect():
            assert min(r["d"], edits + 1) == min(distance(r["a"], r["b"]), edits + 1), (r["a"], r["b"], edits)


def classes_by_brute_force(lines: list[str], edits: int, per: int) -> list[int]:
    parent = list(range(len(lines)))

    def find(i: int) -> int:
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(lines)):
        for j in range(i):
            most = min(edits, min(len(lines[i]), len(lines[j])) // per)
            if lines[i] == lines[j] or (abs(len(lines[i]) - len(lines[j])) <= most and distance(lines[i], lines[j]) <= most):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(lines))]


def check(spark, docs: list[tuple[int, str | None]], edits: int, per: int) -> None:
    lines, where = [], []
    for doc_id, text in docs:
        for no, line in enumerate((text or "").split("\n")):
            if line.strip(" \t\r\x0b\x0c"):
                lines.append(line)
                where.append((doc_id, no))
    order = sorted(range(len(lines)), key=lambda i: where[i])
    lines, where = [lines[i] for i in order], [where[i] for i in order]
    classes = classes_by_brute_force(lines, edits, per)
    expected: dict[int, list[int]] = {d: [] for d, _ in docs}
    for i, c in enumerate(classes):
        if c != i and where[i] != where[c]:
            expected[where[i][0]].append(where[i][1])
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["removed_lines"] for r in L.repeated_lines(df, max_edits=edits, chars_per_edit=per).collect()}
    assert got == {d: sorted(v) for d, v in expected.items()}


def test_against_brute_force(spark):
    rng = random.Random(5)
    base = ["".join(rng.choice("abcdef ") for _ in range(rng.randint(30, 50))) for _ in range(12)]
    docs: list[tuple[int, str | None]] = []
    for d in range(30):
        parts = [edited(rng, rng.choice(base), rng.randint(0, 3)) for _ in range(rng.randint(0, 5))]
        docs.append((d, "\n".join([*parts, "short", " \t", "shorx"])))
    docs += [(100, None), (101, ""), (102, "\n\n")]
    check(spark, docs, 1, 10)
    check(spark, docs, 2, 10)


def test_chain_of_near_lines_and_a_large_family(spark):
    a = "the quick brown fox jumps over the lazy dog again and again"
    chain = [a[:i] + "#" * 0 + a[i:].replace("again", "again" + "x" * i, 1) for i in range(6)]
    family = [a[:i] + "~" + a[i + 1 :] for i in range(len(a))]
    check(spark, [(i, t) for i, t in enumerate([*chain, *family])], 1, 10)


def test_cleaned_texts_keep_other_columns(spark):
    df = spark.createDataFrame([(1, "alpha line that is long enough to count\nkeep", 7), (2, "alpha line that is long enough to count\nmore", 8)], "doc_id long, text string, no int")
    got = {r["doc_id"]: (r["text"], r["no"]) for r in L.without_repeated(df).collect()}
    assert got == {1: ("alpha line that is long enough to count\nkeep", 7), 2: ("more", 8)}
    assert L.repeated_lines(df.filter("false")).count() == 0


def test_common_ends_of_very_long_lines(spark):
    tail = "0123456789" * 220_000
    rows = [("é" + tail, "x" + tail), (tail + "é", tail + "x"), (tail + "é" + tail, tail + tail)]
    df = spark.createDataFrame(rows, "x string, y string")
    assert sorted((r["x"], r["y"]) for r in L.trimmed(df).collect()) == [("é", ""), ("é", "x"), ("é", "x")]
    docs = spark.createDataFrame([(1, "é" + tail), (2, "x" + tail)], "doc_id long, text string")
    assert {r["doc_id"]: r["removed_lines"] for r in L.repeated_lines(docs, max_edits=1).collect()} == {1: [], 2: [0]}


def test_registered_setting_links_lines_of_three_edits(spark, tmp_path):
    from foretell.llm.queries import op5_line_dedup

    licence = "Copyright 2019 the authors; redistribution and use in source and binary forms are permitted"
    docs = [
        (1, licence),
        (2, licence.replace("2019", "2021")),
        (3, licence.replace("2019", "2187")),
        (4, licence.replace("2019", "3456")),
        (5, licence.replace("authors", "writer")),
        (6, "a" + licence[:40] + licence[41:80] + "~" + licence[80:]),
    ]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r["removed_lines"] for r in op5_line_dedup(spark, str(tmp_path)).collect()}
    assert distance(docs[0][1], docs[2][1]) == 3 and distance(docs[0][1], docs[5][1]) == 3
    assert min(distance(docs[k][1], docs[4][1]) for k in (0, 1, 2, 3, 5)) > 3
    assert min(distance(docs[k][1], docs[3][1]) for k in (0, 1, 2, 4, 5)) > 3
    assert got == {1: [], 2: [0], 3: [0], 4: [], 5: [], 6: [0]}


def test_three_edits_against_brute_force(spark):
    rng = random.Random(11)
    base = ["".join(rng.choice("abcdef ") for _ in range(rng.randint(30, 60))) for _ in range(10)]
    docs = [(d, "\n".join(edited(rng, rng.choice(base), rng.randint(0, 4)) for _ in range(rng.randint(1, 4)))) for d in range(30)]
    check(spark, docs, 3, 10)


def test_short_lines_and_limits_of_ranges_against_brute_force(spark):
    rng = random.Random(12)
    base = ["".join(rng.choice("abc") for _ in range(n)) for n in (7, 9, 10, 11, 12, 19, 20, 21, 22, 29, 30, 31, 33, 45, 46, 47, 48, 61, 62, 63)]
    docs = [(d, "\n".join(edited(rng, rng.choice(base), rng.randint(0, 4)) for _ in range(rng.randint(1, 5)))) for d in range(60)]
    check(spark, docs, 3, 10)
    check(spark, docs, 2, 8)


def test_parts_of_a_shared_key_lose_no_pair(spark, monkeypatch):
    monkeypatch.setattr(L, "PART_PAIRS", 7)
    head = "every line of this table begins with the same words and "
    rng = random.Random(13)
    words = ["".join(rng.choice("abcdefgh") for _ in range(12)) for _ in range(25)]
    check(spark, [(d, head + edited(rng, rng.choice(words), rng.randint(0, 3))) for d in range(70)], 3, 10)
