"""N-gram Jaccard join by grouped prefixes.

A document is the set of its distinct word shingles (64-bit hashes).  Under one global order of
shingles two sets of similarity t share a shingle among their first ``n - ceil(t n) + 1``; the
order is by rarity: shingles of one document only, shingles of few, common ones, and by hash
inside a class.  The classes are told by two bit filters of bounded size that are built from
exact counts of all shingles: whatever the filters say defines the order, so their false
positives cost time and never links.

1. Count the shingles of all documents (packed by hash range) and keep two filters: in two or
   more documents, and common.
2. Take every document's prefix and drop its unshared shingles.  Most documents have nothing
   left and can be similar to none but their copies; the others are collapsed by what is left
   of the prefix, size and number of unshared shingles into groups.
3. Star round: at a few of its shingles every group meets two leaders per size class; the best
   leaders of a group are verified, so that large families become components without their pairs.
4. Partner round: groups that share a prefix shingle but lie in different components are each
   verified against a few partners.
5. Join round: groups that still lie in different components are filtered by size and by the places of what they share, expanded to their distinct sets and
   verified exactly.

Links inside one component that are not needed for it are left out; no link between documents
of different components is.

Defined results: a null text or one without words has size 0 and is linked with nothing; fewer
words than ``n`` are one shingle; equal sets are linked; a repeated row gets one result row per
repetition; rows with a null id are judged alike (a component of null ids alone has id null).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import materialise, release
from .components import components

#: Documents that have a shingle from which it counts as common.
COMMON = 16
#: Bits of either filter: per document, and the bounds of the whole.
FILTER_BITS, LEAST_BITS, MOST_BITS = 256, 1 << 16, 1 << 30
#: Documents per hash range in counting.
RANGE_DOCS = 2000
#: Shingle hashes that a task gathers before it packs them.
PACK = 2_000_000
#: Prefix shingles at which a group looks for leaders, and leaders it is verified against.
STAR_TOKENS, STAR_LEADERS = 6, 4


class Rule:
    """Sizes that follow from the threshold ``num / den`` (intersection over union)."""

    def __init__(self, num: int, den: int):
        self.num, self.den = num, den

    def prefix(self, n: int) -> int:
        return n + (-self.num * n // self.den) + 1 if n else 0

    def prefix_sql(self, n: str) -> str:
        return f"({n} - cast(ceil({self.num} * {n} / {self.den}.0) as int) + 1)"

    def overlap_sql(self, a: str, b: str) -> str:
        return f"cast(ceil({self.num} * ({a} + {b}) / {self.num + self.den}.0) as int)"

    def sizes_fit(self, a: str, b: str) -> Column:
        return F.expr(f"{self.den} * least({a}, {b}) >= {self.num} * greatest({a}, {b})")

    def unshared_fit(self, a: str, b: str, ua: str, ub: str) -> Column:
        """Neither document has more unshared shingles than the overlap of a similar pair leaves room for."""
        return F.expr(f"{self.overlap_sql(a, b)} <= least({a} - {ua}, {b} - {ub})")

    def places_fit(self, a: str, b: str, pa_: str, pb: str) -> Column:
        """A first shared shingle at these places (from 0) leaves enough shingles for the overlap of a similar pair."""
        return F.expr(f"{self.overlap_sql(a, b)} <= least({a} - {pa_}, {b} - {pb})")


class Bits:
    """A bit filter cut into one slice per hash range."""

    def __init__(self, ranges: int, slice_bits: int):
        self.shift, self.slice_bits = 64 - (ranges.bit_length() - 1), slice_bits
        self.bits = np.zeros(ranges * (slice_bits // 8), np.uint8)

    def put(self, at: int, data: bytes) -> None:
        size = self.slice_bits // 8
        self.bits[at * size : (at + 1) * size] = np.frombuffer(data, np.uint8)

    def has(self, tokens: np.ndarray) -> np.ndarray:
        base = (tokens >> np.uint64(self.shift)).astype(np.int64) * self.slice_bits if self.shift < 64 else np.zeros(len(tokens), np.int64)
        out = np.ones(len(tokens), bool)
        for at in _probes(_remainder(tokens, self.shift), self.slice_bits):
            out &= (self.bits[(base + at) >> 3] >> (at & 7).astype(np.uint8)) & 1 > 0
        return out


def _remainder(tokens: np.ndarray, shift: int) -> np.ndarray:
    """The 32 bits below the range's."""
    return ((tokens << np.uint64(64 - shift) if shift < 64 else tokens) >> np.uint64(32)).astype(np.uint32)


def _probes(rest: np.ndarray, slice_bits: int) -> Iterator[np.ndarray]:
    h = K.mix64(rest.astype(np.uint64) + np.uint64(1))
    for s in (0, 32):
        yield ((h >> np.uint64(s)) & np.uint64(slice_bits - 1)).astype(np.int64)


def _filters(docs: DataFrame, n: int, total: int) -> tuple[Bits, Bits]:
    ranges = 1 << max(4, min(20, (total // RANGE_DOCS).bit_length()))
    size = 1 << (min(MOST_BITS, max(LEAST_BITS, total * FILTER_BITS)) - 1).bit_length()
    slice_bits = max(64, size // ranges)
    shift = 64 - (ranges.bit_length() - 1)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def flush(held: list[np.ndarray]) -> pa.RecordBatch:
            tokens = np.sort(np.concatenate(held))
            # a shingle of most documents is told once more than makes it common, not each time
            tokens = tokens[np.concatenate((np.ones(min(len(tokens), COMMON + 1), bool), tokens[COMMON + 1 :] != tokens[: -COMMON - 1]))]
            cut = np.searchsorted(tokens, np.arange(ranges, dtype=np.uint64) << np.uint64(shift))
            rest = _remainder(tokens, shift)
            stop = [*cut[1:].tolist(), len(tokens)]
            rows = [(r, rest[a:b].tobytes()) for r, (a, b) in enumerate(zip(cut.tolist(), stop, strict=True)) if b > a]
            return pa.RecordBatch.from_arrays([pa.array([r for r, _ in rows], pa.int32()), pa.array([d for _, d in rows], pa.binary())], ["range", "tokens"])

        held, size = [], 0
        for batch in batches:
            for s in K.shingle_sets(batch.column("text"), n):
                held.append(s)
                size += len(s)
                if size >= PACK:
                    yield flush(held)
                    held, size = [], 0
        if size:
            yield flush(held)

    def count(group: pa.Table) -> pa.Table:
        rest = np.concatenate([np.frombuffer(b.as_py(), np.uint32) for b in group.column("tokens")])
        value, times = np.unique(rest, return_counts=True)
        out = []
        for own in (value[times > 1], value[times > COMMON]):
            bits = np.zeros(slice_bits, np.uint8)
            for at in _probes(own, slice_bits):
                bits[at] = 1
            out.append(np.packbits(bits, bitorder="little").tobytes())
        return pa.table({"range": pa.array([group.column("range")[0].as_py()], pa.int32()), "shared": pa.array([out[0]], pa.binary()), "common": pa.array([out[1]], pa.binary())})

    packed = docs.select("text").mapInArrow(pack, "range int, tokens binary")
    # two slices per range: twice MOST_BITS bits in all at most, which the driver takes one partition at a time
    out = (Bits(ranges, slice_bits), Bits(ranges, slice_bits))
    for row in packed.groupBy("range").applyInArrow(count, "range int, shared binary, common binary").toLocalIterator():
        out[0].put(row["range"], row["shared"])
        out[1].put(row["range"], row["common"])
    return out


def _signatures(docs: DataFrame, n: int, rule: Rule, filters: tuple[Bits, Bits], id_type: str) -> DataFrame:
    """id, n, sid (digest of the set), u (unshared shingles), gid (digest of the group), tokens
    (shared prefix shingles) and first (where the common ones among them begin)."""
    shared = docs.sparkSession.sparkContext.broadcast(filters)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        paired, common = shared.value
        for batch in batches:
            sizes, sids, gids, alone, tokens, first, ends = [], [], [], [], [], [], [0]
            for s in K.shingle_sets(batch.column("text"), n):
                p, met = rule.prefix(len(s)), s[paired.has(s)]
                u = len(s) - len(met)
                kept, rare = met[:0], 0
                if u < p:
                    late = common.has(met)
                    rare = len(met) - int(late.sum())
                    kept = np.concatenate((met[~late], met[late]))[: p - u]
                first.append(min(rare, len(kept)))
                sizes.append(len(s))
                alone.append(u)
                sids.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                gids.append(xxhash.xxh3_128_digest(kept.tobytes() + len(s).to_bytes(8, "little") + u.to_bytes(8, "little")) if len(kept) else None)
                tokens.append(kept)
                ends.append(ends[-1] + len(kept))
            flat = np.concatenate([*tokens, np.empty(0, np.uint64)]).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(sizes, pa.int32()), pa.array(sids, pa.binary()), pa.array(alone, pa.int32()), pa.array(gids, pa.binary()), pa.array(first, pa.int32()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat))], ["id", "n", "sid", "u", "gid", "first", "tokens"])

    return docs.mapInArrow(run, f"id {id_type}, n int, sid binary, u int, gid binary, first int, tokens array<bigint>")


def _shared_postings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by shingle, those whose shingle stands in two rows or more.

    One row is held back between batches; a run of any length streams through.
    """
    held: pa.RecordBatch | None = None
    held_kept = False
    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([held, batch] if held is not None else [batch]).combine_chunks().to_batches()[0]
        tok = table.column("tok").to_numpy(zero_copy_only=False)
        same = tok[1:] == tok[:-1]
        keep = np.concatenate((same, [False])) | np.concatenate(([held_kept], same))
        last = table.num_rows - 1
        held, held_kept = table.slice(last, 1), bool(last and same[-1]) or (last == 0 and held_kept)
        out = keep[:last]
        if out.any():
            yield table.slice(0, last).filter(pa.array(out))
    if held is not None and held_kept:
        yield held


def _verified(docs: DataFrame, sets: DataFrame, pairs: DataFrame, n: int, rule: Rule, id_type: str) -> DataFrame:
    """Those of ``pairs`` (a, b: sids) whose sets are similar, by exact intersection."""
    spark = docs.sparkSession
    wanted = pairs.select(F.col("a").alias("sid")).unionByName(pairs.select(F.col("b").alias("sid"))).distinct()
    wanted = materialise(wanted.join(sets.select("sid", "rid"), "sid").select("sid", "rid", F.xxhash64("rid").alias("h")), "jaccard-wanted")
    # a filter of bounded size tells which texts to look at
    size = 1 << (min(MOST_BITS, max(LEAST_BITS, wanted.count() * 16)) - 1).bit_length()
    places = wanted.select(F.explode(F.array(*[F.shiftrightunsigned("h", s).bitwiseAND(size - 1) for s in (0, 31)])).alias("at"))
    words = places.groupBy(F.shiftright("at", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(at & 63 as int))")).alias("m")).toArrow()
    bits = np.zeros(size // 64, np.int64)
    bits[words.column("w").to_numpy()] = words.column("m").to_numpy()
    shared = spark.sparkContext.broadcast(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in batches:
            h = batch.column("h").to_numpy(zero_copy_only=False).view(np.uint64)
            keep = np.ones(len(h), bool)
            for s in (0, 31):
                at = (h >> np.uint64(s)) & np.uint64(size - 1)
                keep &= (table[(at >> np.uint64(6)).astype(np.int64)].view(np.uint64) >> (at & np.uint64(63))) & np.uint64(1) > 0
            some = batch.filter(pa.array(keep))
            sids, data = [], []
            for s in K.shingle_sets(some.column("text"), n):
                sids.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                data.append(s.tobytes())
            yield pa.RecordBatch.from_arrays([some.column("id"), pa.array(sids, pa.binary()), pa.array(data, pa.binary())], ["id", "sid", "data"])

    texts = docs.select("id", "text", F.xxhash64("id").alias("h")).mapInArrow(run, f"id {id_type}, sid binary, data binary")
    own = wanted.select(F.col("rid").alias("id"), "sid")
    data = texts.join(own, (texts["sid"] == own["sid"]) & texts["id"].eqNullSafe(own["id"]), "left_semi").select("sid", "data")
    data = materialise(data.dropDuplicates(["sid"]), "jaccard-sets")
    both = pairs.join(data.select(F.col("sid").alias("a"), F.col("data").alias("x")), "a").join(data.select(F.col("sid").alias("b"), F.col("data").alias("y")), "b")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("x"), batch.column("y"), strict=True):
                u, v = (np.frombuffer(z.as_buffer(), np.uint64) for z in (x, y))
                common = len(u) + len(v) - len(np.unique(np.concatenate((u, v))))
                keep.append(rule.den * common >= rule.num * (len(u) + len(v) - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    out = materialise(both.select("a", "b", "x", "y").mapInArrow(compare, "a binary, b binary"), "jaccard-links")
    release(wanted, data)
    return out


def _across(post: DataFrame, grouped: DataFrame, found: DataFrame, rule: Rule) -> tuple[DataFrame, DataFrame]:
    """(sid, gid, comp) of all groups' sets, and the meetings (g1, c1, g2, c2) of groups of different
    components at a shingle.  At every shingle the largest component meets the others, never itself."""
    placed = grouped.join(found.withColumnRenamed("node", "sid"), "sid", "left").select("sid", "gid", F.coalesce("component", "sid").alias("comp"))
    placed = materialise(placed, "jaccard-placed")
    tokens = post.join(placed.select("gid", "comp").distinct(), "gid")
    major = tokens.groupBy("tok", "comp").agg(F.count(F.lit(1)).alias("m")).groupBy("tok").agg(F.max_by("comp", F.struct("m", "comp")).alias("major"), F.count(F.lit(1)).alias("comps")).filter("comps > 1").select("tok", "major")
    tokens = materialise(tokens.join(major, "tok"), "jaccard-across")
    side = lambda k: [F.col("gid").alias(f"g{k}"), F.col("comp").alias(f"c{k}"), F.col("n").alias(f"n{k}"), F.col("pos").alias(f"p{k}"), F.col("fc").alias(f"fc{k}"), F.col("late").alias(f"late{k}")]
    minor = tokens.filter("comp <> major").select("tok", *side(1))
    other = tokens.select("tok", *side(2), (F.col("comp") == F.col("major")).alias("main"))
    # what two documents share first stands early in both; and two that have one first common
    # shingle meet there, not again at later ones
    met = minor.join(other, "tok").filter("c1 <> c2 and (main or c1 < c2)").filter(rule.sizes_fit("n1", "n2")).filter(rule.places_fit("n1", "n2", "p1", "p2")).filter("not coalesce(late1 and late2 and fc1 = fc2, false)")
    return placed, met.select("g1", "c1", "g2", "c2", "p2")


def link(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", n: int = 4, num: int = 85, den: int = 100) -> DataFrame:
    """One row per document row: id, n_shingles, component_id (least id of its component)."""
    rule, id_type = Rule(num, den), docs.schema[id_col].dataType.simpleString()
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    total = docs.count()
    filters = _filters(docs, n, total)
    sig = materialise(_signatures(docs, n, rule, filters, id_type), "jaccard-sig")
    sets = materialise(sig.filter("n > 0").groupBy("sid").agg(F.min("id").alias("rid"), F.min("gid").alias("gid")), "jaccard-distinct")
    grouped = sets.filter("gid is not null").select("sid", "gid")
    groups = sig.filter("gid is not null").dropDuplicates(["gid"])
    begin = F.when(F.col("first") < F.size("tokens"), F.col("first")).otherwise(F.lit(0))
    lead = F.get("tokens", F.col("first"))  # the first common shingle, if any
    groups = groups.select("gid", "n", "u", (F.col("u") + F.col("first")).alias("rare"), begin.alias("begin"), "first", lead.alias("fc"), F.posexplode("tokens").alias("at", "tok"))
    groups = groups.select("gid", "n", "u", "rare", "fc", (F.col("u") + F.col("at")).alias("pos"), (F.col("at") > F.col("first")).alias("late"), F.col("at").between(F.col("begin"), F.col("begin") + STAR_TOKENS - 1).alias("star"), "tok")
    parts = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    post = groups.repartition(parts, "tok").sortWithinPartitions("tok").mapInArrow(_shared_postings, "gid binary, n int, u int, rare int, fc bigint, pos int, late boolean, star boolean, tok bigint")
    post = materialise(post, "jaccard-post")

    # star round: a leader is the member with the fewest rare shingles, the likeliest original
    step = math.log(den / num)
    classed = post.filter("star").withColumn("c", F.floor(F.log(F.col("n").cast("double")) / step).cast("int"))
    one = F.struct("rare", "gid", "n", "u")
    leaders = classed.groupBy("tok", "c").agg(F.min(one).alias("l"), F.min_by(one, F.xxhash64("gid")).alias("m"))
    leaders = leaders.select("tok", "c", F.explode(F.array_distinct(F.array("l", "m"))).alias("l"))
    leaders = leaders.select("tok", F.explode(F.array(F.col("c") - 1, "c", F.col("c") + 1)).alias("c"), F.col("l.gid").alias("lead"), F.col("l.n").alias("lead_n"), F.col("l.u").alias("lead_u"), F.col("l.rare").alias("lead_rare"))
    met = classed.join(leaders, ["tok", "c"]).filter("gid <> lead").filter(rule.sizes_fit("n", "lead_n")).filter(rule.unshared_fit("n", "lead_n", "u", "lead_u"))
    best = met.groupBy("gid", "n", "lead", "lead_n", "lead_rare").agg(F.count(F.lit(1)).alias("k"))
    # a group meets at most 6 * STAR_TOKENS leaders
    rank = F.struct((-F.col("k")).alias("k"), F.abs(F.col("n") - F.col("lead_n")).alias("d"), F.col("lead_rare").alias("r"), "lead")
    best = best.groupBy("gid").agg(F.slice(F.array_sort(F.collect_list(rank)), 1, STAR_LEADERS).alias("l")).select("gid", F.explode("l.lead").alias("lead"))
    heads = grouped.groupBy("gid").agg(F.min("sid").alias("head"))
    stars = best.join(heads, "gid").select(F.col("head").alias("a"), "lead").join(heads.select(F.col("gid").alias("lead"), F.col("head").alias("b")), "lead").select("a", "b")
    chosen = grouped.groupBy("gid").agg(F.array_distinct(F.array(F.min("sid"), *[F.min_by("sid", F.xxhash64(F.lit(k), F.col("sid"))) for k in range(1, STAR_LEADERS)])).alias("l"))
    inside = grouped.join(chosen.select("gid", F.explode("l").alias("head")), "gid").filter("sid <> head").select(F.col("sid").alias("a"), F.col("head").alias("b"))
    first = _verified(docs, sets, materialise(stars.unionByName(inside).distinct(), "jaccard-pairs"), n, rule, id_type)
    found = materialise(components(first), "jaccard-first")

    # partner round: of what still meets across components, each group is verified against a few partners
    placed, across = _across(post, grouped, found, rule)
    heads = placed.groupBy("gid", "comp").agg(F.min("sid").alias("head"))
    # partners where the shared shingle stands earliest have the fewest rare ones, so the best chance
    partner = F.struct("g2", "c2")
    order = lambda k: F.struct("p2", F.xxhash64(F.lit(k), F.col("g1"), F.col("c1"), F.col("g2"), F.col("c2")))
    picks = across.groupBy("g1", "c1").agg(F.array_distinct(F.array(*[F.min_by(partner, order(k)) for k in range(2 * STAR_LEADERS)])).alias("l"))
    picks = picks.select("g1", "c1", F.explode("l").alias("p")).select("g1", "c1", "p.g2", "p.c2")
    near = picks.join(heads.select(F.col("gid").alias("g1"), F.col("comp").alias("c1"), F.col("head").alias("a")), ["g1", "c1"]).join(heads.select(F.col("gid").alias("g2"), F.col("comp").alias("c2"), F.col("head").alias("b")), ["g2", "c2"]).select("a", "b").distinct()
    more = _verified(docs, sets, materialise(near, "jaccard-pairs"), n, rule, id_type)
    found = materialise(components(found.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more)), "jaccard-first")

    # join round: whatever is left across components
    placed, across = _across(post, grouped, found, rule)
    across = across.select("g1", "c1", "g2", "c2").distinct()
    nodes = placed.select("gid", "comp").distinct()
    mixed = nodes.groupBy("gid").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).filter("low <> high").select("gid")
    alike = nodes.join(mixed, "gid")
    alike = alike.select(F.col("gid").alias("g1"), F.col("comp").alias("c1")).join(alike.select(F.col("gid").alias("g2"), F.col("comp").alias("c2")), (F.col("g1") == F.col("g2")) & (F.col("c1") < F.col("c2")))
    wide = across.unionByName(alike.select("g1", "c1", "g2", "c2"))
    members = placed.select("sid", "gid", "comp")
    pairs = wide.join(members.select(F.col("sid").alias("a"), F.col("gid").alias("g1"), F.col("comp").alias("c1")), ["g1", "c1"]).join(members.select(F.col("sid").alias("b"), F.col("gid").alias("g2"), F.col("comp").alias("c2")), ["g2", "c2"]).select("a", "b").distinct()
    second = _verified(docs, sets, materialise(pairs, "jaccard-pairs"), n, rule, id_type)

    # a component's links stand for it by its first round's stars
    links = found.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(second.select("a", "b"))
    final = components(links).select(F.col("node").alias("sid"), "component")
    rows = sig.select("id", "n", "sid").join(final, "sid", "left").withColumn("component", F.coalesce("component", "sid"))
    least = sets.join(final, "sid", "left").withColumn("component", F.coalesce("component", "sid")).groupBy("component").agg(F.min("rid").alias("component_id"))
    out = rows.join(least, "component", "left")
    return out.select(F.col("id").alias(id_col), F.col("n").cast("long").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"))


def one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", n: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """The rows of ``docs`` that stay when each component keeps one: the row of least id (one row
    of a repeated id; of texts that share this id the first).  Documents without words stay,
    and so do rows without an id."""
    found = link(docs, id_col=id_col, text_col=text_col, n=n, num=num, den=den)
    stay = found.filter("n_shingles > 0").select(F.col("component_id").alias("_stay")).dropna().distinct()
    row = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), F.col(id_col).alias("_id"), (F.coalesce(F.regexp_instr(F.col(text_col), F.lit(r"[^\x20\x09-\x0D]")), F.lit(0)) > 0).alias("_words"))
    linked = row.filter("_words and _id is not null").join(stay, F.col("_id") == F.col("_stay"), "left_semi")
    linked = linked.dropDuplicates(["_id"])
    rest = row.filter("not _words or _id is null")
    return linked.select("_row.*").unionByName(rest.select("_row.*"))
