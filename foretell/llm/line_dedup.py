"""Line deduplication by a segment-partition edit join, in DataFrame operations only.

Two lines are linked when their edit distance (in code points) is at most ``max_edits`` and at most
one per ``chars_per_edit`` characters of the shorter line: one rule for lines of every length.

Lines are indexed by ranges of length.  A line that may have t edits is cut into t + 1 segments of
a size that the range fixes, the first half of them counted from the line's beginning, the others
from its end.  t edits cannot spoil all: some segment with i others outside it stands unchanged,
moved by i places at most, seen from its own end of the line.  So a line probes each range that its
partner's length may be in with 2 i + 1 substrings for that segment, (t + 1)^2 / 2 in all, whatever
the difference of the lengths.  What meets is verified with a banded bit-parallel edit distance
that keeps one word of 2 * max_edits + 1 diagonals per step.

A key that many lines share costs no pairs: first every line meets one leader per key and the
verified links become components; then only lines of different components meet, and a count of
letters turns most of them away inside the join.

Defined results: null texts have no lines; lines without a word are kept and never linked; of
each class the first line in (id, line number) order stays; repeated rows are judged alike;
lines of any length are compared whole.  Lines count as equal when two independent 64-bit hashes
and thus 128 bits agree.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, salted_join
from .components import components

MAX_EDITS, CHARS_PER_EDIT = 3, 10
#: Lengths in one range of the index (shorter lines: one range per number of edits).
RANGE = 16
#: Comparisons (of letter counts) that one part of a key's pairs is aimed at.
PART_PAIRS = 4_000_000
#: Characters whose counts make a signature; with the second group all others are counted together.
COUNTED = ("eantirs", "odhlu ")
#: A count is told in nine bits, by the state of a ring counter: two states differ in as many bits as
#: their counts differ, or in fewer when that is over nine.
RING = 9
#: Where lines are cut for that, in quarters of their range's least length, and how many of COUNTED are told there.
CUTS = {2: 2, 1: 1, 3: 1}
SIGNATURES = [f"sig{cut}{side}{k}" for cut, groups in CUTS.items() for side in "pq" for k in range(groups)]
#: Line numbers (8 bytes each) up to which those that share a key are broadcast; beyond, they join by shuffle.
MAX_BROADCAST_LINES = 2_000_000
#: Longest step of the search for common beginnings and ends; with the smaller ones it covers any string Spark can hold.
LONGEST_STEP = 1 << 30
_SPACE = " \t\n\x0b\x0c\r"


def _worded(line: Column) -> Column:
    return F.btrim(line, F.lit(_SPACE)) != ""


def lines_of(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, no (from 0), line: the lines that have a word."""
    each = F.posexplode(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n")).alias("no", "line")
    return docs.select(F.col(id_col).alias("id"), each).filter(_worded(F.col("line")))


def _with(rows: DataFrame, **columns: Column) -> DataFrame:
    """``rows`` with columns that are worked out once a row; as plain expressions they would be worked
    out again wherever a later expression names them."""
    return rows.select("*", F.inline(F.array(F.struct(*[c.alias(name) for name, c in columns.items()]))))


def described(lines: DataFrame, edits: int, per: int) -> DataFrame:
    """``lines`` with n (length), once for the range of their length and, where a partner may be shorter
    and in the range below, once more for that: low (whether it is that), number, and the range's size
    of segments and least length."""
    lines = _with(lines, n=F.length("line"))
    lines = _with(lines, here=_range(F.col("n"), edits, per), below=_range(F.greatest(F.col("n") - edits, F.lit(0)), edits, per))
    here, below = (F.struct(F.lit(low).alias("low"), F.col(of).alias("number")) for low, of in ((False, "here"), (True, "below")))
    both = F.inline(F.when(F.col("below") < F.col("here"), F.array(here, below)).otherwise(F.array(here)))
    lines = lines.select(*[c for c in lines.columns if c not in ("here", "below")], both)
    return _with(lines, size=_segment_size(F.col("number"), edits, per), least=_least_length(F.col("number"), edits, per).cast("int"))


def _div(a: Column, b: Column | int) -> Column:
    return ((a - a % b) / b).cast("int")


def allowed_edits(n: Column, edits: int, per: int) -> Column:
    """Edits that a pair may have whose shorter line has ``n`` characters."""
    return F.least(F.lit(edits), _div(n, per))


def _range(n: Column, edits: int, per: int) -> Column:
    """Number of the range of lengths; up to ``edits`` it is the number of edits allowed."""
    return F.when(n < edits * per, _div(n, per)).otherwise(edits + _div(n - edits * per, RANGE))


def _least_length(number: Column, edits: int, per: int) -> Column:
    return F.when(number < edits, number * per).otherwise(edits * per + (number - edits) * RANGE)


def _segment_size(number: Column, edits: int, per: int) -> Column:
    return _div(_least_length(number, edits, per), F.least(number, F.lit(edits)) + 1)


def _keys(edits: int) -> dict[tuple[bool, int, int], Column]:
    """By (from the end, segment, move): the key of the substring of a described ``line`` where that
    segment of a line in its range may stand; null where there is no such place."""
    n, number, size = F.col("n"), F.col("number"), F.col("size")
    out = {}
    for end in (False, True):
        for i in range((edits + 1) // 2 if end else edits // 2 + 1):
            # from the beginning there are half the segments rounded up, from the end the others
            used = number >= (2 * i + 1 if end else max(1, 2 * i))
            for move in range(-i, i + 1):
                at = (n - (i + 1) * size if end else i * size) + move
                key = F.xxhash64(F.lit(2 * i + end), number, F.substring("line", at + 1, size))
                out[end, i, move] = F.when(used & (at >= 0) & (at + size <= n), key)
    return out


def unmoved_keys(edits: int) -> Column:
    """The keys of a line's segments at their own places.  In the range of its length they are its index,
    and they probe for lines of equal length."""
    return F.array(*[k for (_, _, move), k in _keys(edits).items() if move == 0])


def moved_keys(edits: int) -> Column:
    """The keys of the other places at which a line of equal or smaller length may have a segment."""
    return F.array(*[k for (_, _, move), k in _keys(edits).items() if move]).cast("array<bigint>")


def _ring(count: Column) -> Column:
    full = (1 << RING) - 1
    states = [((1 << m) - 1) if m < RING else full ^ ((1 << (m - RING)) - 1) for m in range(2 * RING)]
    return F.element_at(F.lit(np.asarray(states, np.int64)), count % (2 * RING) + 1)


def signatures(*cuts: int) -> dict[str, Column]:
    """Counts of characters before each cut and after it, seven in a number.

    What is before is measured from the line's beginning and what is after from its end, and neither
    is longer than its share of the range's least length.  An edit moves the sum of differences
    of two lines' counts by two at most: a replacement on one side, and an insertion takes in one
    character and pushes out another.  The sides do not overlap, so their edits add up."""
    out = {}
    for cut in cuts:
        before = _div(F.col("least") * cut, 4)
        for side, start, size in (("p", F.lit(1), before), ("q", F.col("n") - F.col("least") + before + 1, F.col("least") - before)):
            part, rest = F.substring("line", start, size), size
            for k, members in enumerate(COUNTED[: CUTS[cut]]):
                number = F.lit(0).cast("long")
                for i, c in enumerate(members):
                    # with the character taken out as often as it stands, the length tells how often
                    count = size - F.length(F.replace(part, F.lit(c), F.lit("")))
                    number, rest = number.bitwiseOR(F.shiftleft(_ring(count), RING * i)), rest - count
                out[f"sig{cut}{side}{k}"] = number.bitwiseOR(F.shiftleft(_ring(rest), RING * len(members))) if len(members) < 7 else number
    return out


def _signatures_fit(a: str, b: str, edits: int) -> Column:
    """Whether the signature columns with suffixes ``a`` and ``b`` leave room for a link, at every cut."""
    fits = F.lit(True)
    for cut in CUTS:
        total = F.lit(0)
        for name in (f"sig{cut}{side}{k}" for side in "pq" for k in range(CUTS[cut])):
            total = total + F.bit_count(F.col(name + a).bitwiseXOR(F.col(name + b)))
        fits = fits & (total <= 2 * edits)
    return fits


def _signed(rows: DataFrame, texts: DataFrame, edits: int) -> DataFrame:
    """``rows`` with the signatures and unmoved keys of their lines as lines of the range they are here for."""
    unmoved = {f"u{k}": F.get(unmoved_keys(edits), F.lit(k)) for k in range(edits + 1)}
    # in two parts: the code for all at once is more than the JVM compiles
    for columns in (signatures(2) | unmoved, signatures(1, 3)):
        rows = rows.join(texts.select("line_id", "low", *[c.alias(name) for name, c in columns.items()]), ["line_id", "low"])
    return rows.drop("low")


def _common(a: str, b: str, end: bool) -> Column:
    """Length of the common beginning (or end) of two string columns, by halving steps."""
    most = F.least(F.length(a), F.length(b))
    steps = F.filter(F.array(*[F.lit(1 << k) for k in range(LONGEST_STEP.bit_length() - 1, -1, -1)]), lambda s: s <= most)
    part = lambda c, at, s: F.substring(F.col(c), (F.length(c) - at - s + 1) if end else at + 1, s)

    def longer(at: Column, s: Column) -> Column:
        return F.when((s <= most - at) & (part(a, at, s) == part(b, at, s)), at + s).otherwise(at)

    return F.aggregate(steps, F.lit(0), longer)


def trimmed(pairs: DataFrame) -> DataFrame:
    """``pairs`` with x and y without their common beginning and end, which no best alignment touches."""
    # written between the steps: an expression would be evaluated again wherever it is named
    cut = materialise(pairs.withColumn("_head", _common("x", "y", False)), "line-heads")
    cut = cut.withColumn("x", F.substring(F.col("x"), F.col("_head") + 1, F.length("x"))).withColumn("y", F.substring(F.col("y"), F.col("_head") + 1, F.length("y"))).drop("_head")
    cut = materialise(cut, "line-cut")
    cut = materialise(cut.withColumn("_tail", _common("x", "y", True)), "line-tails")
    return cut.withColumn("x", F.substring(F.col("x"), F.lit(1), F.length("x") - F.col("_tail"))).withColumn("y", F.substring(F.col("y"), F.lit(1), F.length("y") - F.col("_tail"))).drop("_tail")


def banded_distance(a: Column, b: Column, edits: int) -> Column:
    """Edit distance of two strings if at most ``edits`` (else some larger number).

    Bit k of a step's words stands for row ``step - edits + k`` of the distance matrix; the value
    is followed along the lowest diagonal until it reaches the last row, then along that row.  No
    value of a step is less than that one minus the number of rising bits; once even that is too
    large, the other steps are passed over.
    """
    width = 2 * edits + 1
    full = (1 << width) - 1
    rows, cols = F.split(a, ""), F.split(b, "")
    lit = lambda v: F.lit(v).cast("long")
    flip = lambda c: c.bitwiseXOR(lit(full))

    def step(state: Column, at: Column) -> Column:
        vp, vn = state["vp"], state["vn"]
        sign = F.get(state["cols"], at - 1)
        equal = lit(0)
        for k in range(width):
            equal = equal + F.when(F.get(state["rows"], at - edits + k - 1) == sign, lit(1 << k)).otherwise(lit(0))
        zero = lit(0)
        d0 = F.aggregate(F.array(equal), zero, lambda _, e: ((e.bitwiseAND(vp) + vp).bitwiseXOR(vp).bitwiseOR(e).bitwiseOR(vn)).bitwiseAND(lit(full)))
        inner = F.struct(d0.alias("d0"), vp.alias("vp"), vn.alias("vn"))
        # aggregate names a value without copying the state, as transform would
        moved = F.aggregate(F.array(inner), state, lambda kept, s: _advance(s, kept, at))
        return F.when(state["d"] - F.bit_count(vp) > edits, state).otherwise(moved)

    def _advance(s: Column, state: Column, at: Column) -> Column:
        hp = s["vn"].bitwiseOR(flip(s["d0"].bitwiseOR(s["vp"])))
        hn = s["d0"].bitwiseAND(s["vp"])
        down = F.shiftright(s["d0"], 1)
        last = F.size(state["rows"]) - at + edits  # bit of the last row
        falling = F.when(last >= 2 * edits, F.when(s["d0"].bitwiseAND(lit(1 << (2 * edits))) == 0, 1).otherwise(0)).otherwise(
            F.pmod(F.floor(hp / F.pow(F.lit(2.0), last)).cast("int"), F.lit(2)) - F.pmod(F.floor(hn / F.pow(F.lit(2.0), last)).cast("int"), F.lit(2))
        )
        return F.struct(
            hn.bitwiseOR(flip(down.bitwiseOR(hp))).alias("vp"),
            down.bitwiseAND(hp).alias("vn"),
            (state["d"] + falling).cast("int").alias("d"),
            state["rows"].alias("rows"),
            state["cols"].alias("cols"),
        )

    start = F.struct(lit(full - ((1 << edits) - 1)).alias("vp"), lit(0).alias("vn"), F.least(F.lit(edits), F.size(rows)).alias("d"), rows.alias("rows"), cols.alias("cols"))
    near = F.abs(F.length(a) - F.length(b)) <= edits
    steps = F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(b)))
    banded = F.when(F.length(b) == 0, F.length(a)).otherwise(F.aggregate(steps, start, step, lambda s: s["d"]))
    return F.when(near, banded).otherwise(F.lit(edits + 1))


def _inside_fits(a: str, b: str, allowed: Column, edits: int) -> Column:
    """Whether what trimming left can be within ``allowed`` edits, by segments once more.

    Trimmed strings differ in their first and in their last character; when both have two or more,
    those are different edits.  So at most ``allowed`` - 2 are inside, and of one more segments than
    that one stands unchanged in the other string, moved by ``allowed`` places at most."""
    x, y, n = F.col(a), F.col(b), F.length(a)
    inner, met = F.greatest(allowed - 1, F.lit(1)), F.lit(False)
    for k in range(max(1, edits - 1)):
        start = F.lit(2) + _div((n - 2) * k, inner)
        size = F.lit(2) + _div((n - 2) * (k + 1), inner) - start
        place = F.greatest(start - allowed, F.lit(1))
        met = met | ((k < inner) & (F.instr(F.substring(y, place, size + start - place + allowed), F.substring(x, start, size)) > 0))
    return F.when(F.least(n, F.length(b)) < 2, F.greatest(n, F.length(b)) <= allowed + 1).otherwise((allowed >= 2) & met)


def _verified(texts: DataFrame, pairs: DataFrame, edits: int, per: int) -> DataFrame:
    """Those of ``pairs`` (a, b: line numbers) within the rule, by the banded distance of what trimming leaves."""
    lines = texts.select("line_id", "line")
    both = pairs.join(lines.withColumnsRenamed({"line_id": "a", "line": "x"}), "a").join(lines.withColumnsRenamed({"line_id": "b", "line": "y"}), "b")
    both = both.withColumn("allowed", allowed_edits(F.least(F.length("x"), F.length("y")), edits, per)).filter(F.abs(F.length("x") - F.length("y")) <= F.col("allowed"))
    both = materialise(trimmed(both).filter(_inside_fits("x", "y", F.col("allowed"), edits)), "line-rests")
    return materialise(both.filter(banded_distance(F.col("x"), F.col("y"), edits) <= F.col("allowed")).select("a", "b"), "line-links")


def _pairs_across(placed: DataFrame, edits: int) -> DataFrame:
    """(a, b) of lines of different components that share a key and whose letter counts fit.

    At every key the largest component meets the others, never itself.  A key with many pairs is
    cut into parts of the smaller side, which the other side meets one by one, so no task has more
    than about ``PART_PAIRS`` comparisons of one key.
    """
    per = placed.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("m"))
    per = per.groupBy("key").agg(F.max_by("comp", F.struct("m", "comp")).alias("major"), F.count(F.lit(1)).alias("comps"), F.sum("m").alias("m"), F.max("m").alias("most"))
    per = per.filter("comps > 1").withColumn("parts", F.least(F.col("m") - F.col("most"), F.ceil((F.col("m") - F.col("most")) * F.col("m") / PART_PAIRS)).cast("int"))
    across = materialise(salted_join(placed, per.select("key", "major", "m", "parts"), ["key"], "m", placed.count()), "line-across")
    side = lambda k: [F.col("line_id").alias(k), F.col("comp").alias(f"c{k}"), *[F.col(c).alias(f"{c}_{k}") for c in SIGNATURES], F.col("own").alias(f"own_{k}"), F.col("slot").alias(f"slot_{k}"), *[F.col(f"u{i}").alias(f"u{i}_{k}") for i in range(edits + 1)]]
    minor = across.filter("comp <> major").select("key", F.pmod(F.xxhash64("line_id"), F.col("parts")).cast("int").alias("part"), *side("a"))
    other = across.select("key", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), (F.col("comp") == F.col("major")).alias("main"), *side("b"))
    pairs = minor.join(other, ["key", "part"]).filter("ca <> cb and (main or ca < cb) and (own_a or own_b)")
    # two lines that share several segments in place meet at the first of them
    for k in range(edits + 1):
        pairs = pairs.filter((F.col("slot_a") <= k) & (F.col("slot_b") <= k) | ~F.col(f"u{k}_a").eqNullSafe(F.coalesce(f"u{k}_b", F.lit(0))))
    return pairs.filter(_signatures_fit("_a", "_b", edits)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def line_classes(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", max_edits: int = MAX_EDITS, chars_per_edit: int = CHARS_PER_EDIT) -> DataFrame:
    """id, no, class_id, class_check of every line with a word; lines are of one class when both are equal."""
    if max_edits < 1 or chars_per_edit < 2 * (max_edits + 1):
        raise ValueError("at least one edit, and two characters per edit and segment")
    identified = lines_of(docs, id_col, text_col).withColumn("line_id", F.xxhash64("line")).withColumn("check", F.xxhash64(F.lit(1), "line"))
    long_lines = identified.filter(F.length("line") >= chars_per_edit)
    # one row per different line: its keys.  Texts stay where they are
    keyed = described(long_lines, max_edits, chars_per_edit).select("line_id", "low", unmoved_keys(max_edits).alias("unmoved"), moved_keys(max_edits).alias("moved"))
    keyed = materialise(keyed.distinct(), "line-keys")
    each = F.inline(F.array(*[F.struct(F.lit(name == "moved").alias("moved"), F.col(name).alias("keys")) for name in ("unmoved", "moved")]))
    rows = keyed.select("line_id", "low", each.alias("probe", "keys")).select("line_id", "low", "probe", F.posexplode("keys").alias("slot", "key")).filter("key is not null")
    rows = rows.select("line_id", (~F.col("low") & ~F.col("probe")).alias("own"), "low", F.when(F.col("probe"), F.lit(max_edits + 1)).otherwise(F.col("slot")).alias("slot"), "key")
    # a key is of use when some line has it as its own and it stands twice
    times = rows.groupBy("key").agg(F.sum(F.when(F.col("own"), F.lit(1 << 40)).otherwise(F.lit(0)) + 1).alias("t"))
    met = times.filter((F.col("t") > 1 << 40) & (F.col("t").bitwiseAND((1 << 40) - 1) > 1)).select("key")
    rows = materialise(rows.join(met, "key").groupBy("key", "line_id").agg(F.max("own").alias("own"), F.max("low").alias("low"), F.min("slot").alias("slot")), "line-shared")
    # only lines that share a key move with their text, once
    wanted = materialise(rows.select("line_id").distinct(), "line-wanted")
    wanted = F.broadcast(wanted) if wanted.count() <= MAX_BROADCAST_LINES else wanted
    texts = long_lines.join(wanted, "line_id").groupBy("line_id").agg(F.min(F.struct("line", "check")).alias("l")).select("line_id", "l.*")
    texts = materialise(texts, "line-texts")
    rows = materialise(_signed(rows, materialise(described(texts, max_edits, chars_per_edit), "line-described"), max_edits), "line-signed")

    # star round: one leader per key
    leaders = rows.groupBy("key").agg(F.min(F.when(F.col("own"), F.struct("line_id", *SIGNATURES))).alias("l"), F.count(F.lit(1)).alias("m")).filter("m > 1").select("key", "m", F.col("l.line_id").alias("b"), *[F.col(f"l.{c}").alias(f"{c}_b") for c in SIGNATURES])
    stars = salted_join(rows, leaders, ["key"], "m", rows.count()).filter((F.col("line_id") != F.col("b")) & _signatures_fit("", "_b", max_edits))
    stars = materialise(stars.select(F.least("line_id", "b").alias("a"), F.greatest("line_id", "b").alias("b")).distinct(), "line-pairs")
    found = materialise(components(_verified(texts, stars, max_edits, chars_per_edit)), "line-first")

    # join round: only across components
    placed = rows.join(found.withColumnRenamed("node", "line_id"), "line_id", "left").withColumn("comp", F.coalesce("component", "line_id")).drop("component")
    pairs = materialise(_pairs_across(materialise(placed, "line-placed"), max_edits), "line-pairs")
    second = _verified(texts, pairs, max_edits, chars_per_edit)
    links = found.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(second)
    checks = texts.select("line_id", "check")
    final = components(links).join(checks.withColumnsRenamed({"line_id": "component", "check": "class_check"}), "component").join(checks.withColumnRenamed("line_id", "node"), "node")
    out = identified.select("id", "no", "line_id", "check").join(final.withColumnRenamed("node", "line_id"), ["line_id", "check"], "left")
    return out.select("id", "no", F.coalesce("component", "line_id").alias("class_id"), F.coalesce("class_check", "check").alias("class_check"))


def repeated_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", max_edits: int = MAX_EDITS, chars_per_edit: int = CHARS_PER_EDIT) -> DataFrame:
    """One row per document row: id, n_lines (with a word), removed_lines (numbers from 0, sorted)
    of lines that repeat an earlier line of the corpus or are linked with one."""
    lines = materialise(line_classes(docs, id_col=id_col, text_col=text_col, max_edits=max_edits, chars_per_edit=chars_per_edit).select("id", "no", "class_id", "class_check"), "line-classes")
    total = lines.count()
    first = lines.groupBy("class_id", "class_check").agg(F.min(F.struct("id", "no")).alias("first"), F.count(F.lit(1)).alias("m")).filter("m > 1")
    again = salted_join(lines, first, ["class_id", "class_check"], "m", total).filter(~F.struct("id", "no").eqNullSafe(F.col("first")))
    removed = again.select("id", "no").distinct().groupBy("id").agg(F.array_sort(F.collect_list("no")).alias("removed_lines"))
    counted = docs.select(F.col(id_col).alias("id"), F.size(F.filter(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n"), _worded)).alias("n_lines"))
    out = counted.join(removed.withColumnRenamed("id", "_id"), F.col("id").eqNullSafe(F.col("_id")), "left")
    return out.select(F.col("id").alias(id_col), F.col("n_lines").cast("long").alias("n_lines"), F.coalesce("removed_lines", F.array().cast("array<int>")).alias("removed_lines"))


def without_repeated(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", max_edits: int = MAX_EDITS, chars_per_edit: int = CHARS_PER_EDIT) -> DataFrame:
    """``docs`` with the repeated lines taken out of the texts; other columns as they are."""
    judged = repeated_lines(docs, id_col=id_col, text_col=text_col, max_edits=max_edits, chars_per_edit=chars_per_edit)
    judged = judged.select(F.col(id_col).alias("_id"), "removed_lines").filter(F.size("removed_lines") > 0).dropDuplicates(["_id"])
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), F.col(id_col).alias("_own"))
    joined = row.join(judged, F.col("_own").eqNullSafe(F.col("_id")), "left")
    kept = F.array_join(F.filter(F.split(F.col("_row")[text_col], "\n"), lambda x, i: ~F.array_contains("removed_lines", i)), "\n")
    fresh = F.when(F.col("removed_lines").isNull(), F.col("_row")[text_col]).otherwise(kept)
    return joined.withColumn("_fresh", fresh).select(*[(F.col("_fresh") if c == text_col else F.col("_row")[c]).alias(c) for c in docs.columns])
