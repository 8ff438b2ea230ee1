"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Every source gets a target number of words (its weight's share of all words, stopped at ``cap``
times its size with the excess shared again by weight).  A source is cut into blocks by a hash;
its target is so many whole rounds over all blocks and a prefix of one more round's random block
order, the last block taken up to one document and that document up to one word.  The block
draws of all sources are split among the output shards by a binary tree: at each node a
multivariate-hypergeometric draw says how many of each source's draws go left, so shards are
random mixtures with exact quotas.  Shards then own disjoint ranges of each source's permuted
draws, and documents are shuffled inside their shard by a hash.

Defined results: sources stand in code-point order with null last; a null text has size 0 and
is taken 0 words (but travels with its block); repeated rows are taken alike; an empty table
gives an empty mix; reruns agree, because every random choice is a hash or a seeded draw.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import textkernel as K
from .common import materialise

#: Documents per block aimed at, and blocks of one source at most (larger sources get larger blocks).
BLOCK_ROWS, MAX_BLOCKS = 2000, 1 << 16
#: Rows that a part of an output shard is aimed at.
PART_ROWS = 100_000
#: Sources up to which the plan's table (one row each) is broadcast; beyond, it is joined by shuffle.
MAX_BROADCAST_SOURCES = 50_000


def word_sizes(frame: DataFrame, text_col: str, name: str) -> DataFrame:
    """``frame`` without its text and with the number of words of it in column ``name``."""
    kept = [c for c in frame.columns if c != text_col]
    schema = frame.select(*kept).withColumn(name, F.lit(0).cast("long")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [np.diff(c.word_offsets) for c in K.chunks(batch.column(text_col))]
            size = pa.array(np.concatenate([*n, np.empty(0, np.int64)]).astype(np.int64))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), size], [*kept, name])

    return frame.mapInArrow(run, schema)


def targets(sizes: Sequence[int], weights: Sequence[float], cap: float) -> list[float]:
    """Share the sum of ``sizes`` by weight, none above ``cap`` times its own size."""
    out, left, open_ = [0.0] * len(sizes), float(sum(sizes)), list(range(len(sizes)))
    while open_:
        whole = sum(weights[i] for i in open_)
        above = [i for i in open_ if left * weights[i] / whole > cap * sizes[i]]
        if not above:
            for i in open_:
                out[i] = left * weights[i] / whole
            break
        for i in above:
            out[i] = float(cap * sizes[i])
        left -= sum(out[i] for i in above)
        shut = set(above)
        open_ = [i for i in open_ if i not in shut]
    return out


def splitting_tree(draws: Sequence[int], n_shards: int, seed: int) -> np.ndarray:
    """quotas[source, shard] with row sums ``draws`` and column sums as even as can be."""
    rng = np.random.Generator(np.random.PCG64(seed))
    out = np.zeros((len(draws), n_shards), np.int64)

    def split(counts: np.ndarray, lo: int, hi: int) -> None:
        if hi - lo == 1:
            out[:, lo] = counts
            return
        mid = (lo + hi) // 2
        total = int(counts.sum())
        take = total * (mid - lo) // (hi - lo)
        left = rng.multivariate_hypergeometric(counts, take, method="marginals") if total else counts
        split(left, lo, mid)
        split(counts - left, mid, hi)

    if len(draws):
        split(np.asarray(draws, np.int64), 0, n_shards)
    return out


class Plan:
    """What was decided for the sources: one row each, to be joined to documents."""

    def __init__(self, table: DataFrame, blocks: DataFrame, n_sources: int, n_blocks: int, rows: int, seed: int):
        self.table = F.broadcast(table) if n_sources <= MAX_BROADCAST_SOURCES else table
        self.blocks, self.n_blocks, self.rows, self.seed = blocks, n_blocks, rows, seed


def _document_hash(id_col: str, text_col: str, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col(id_col), F.col(text_col))


def _block(document_hash: str, blocks: str) -> Column:
    return F.pmod(F.col(document_hash), F.col(blocks)).cast("int")


def _order(block: str, epoch: Column, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col("_no"), F.col(block), epoch.cast("int"))


def make_plan(digest: DataFrame, *, weights: Sequence[float] = (5, 2, 1), cap: int = 3, n_shards: int = 8, seed: int = 20) -> Plan:
    """``digest``: source, hash, size of every document.  The driver sees one row per source."""
    spark = digest.sparkSession
    found = digest.groupBy("source").agg(F.sum("size").alias("words"), F.count(F.lit(1)).alias("rows")).toPandas()
    found = sorted(found.itertuples(index=False), key=lambda r: (r.source is None, (r.source or "").encode()))
    sizes = [int(r.words) for r in found]
    target = targets(sizes, [weights[i % len(weights)] for i in range(len(found))], cap)
    n_blocks = [min(MAX_BLOCKS, max(min(int(r.rows), 64), math.ceil(r.rows / BLOCK_ROWS))) for r in found]
    full = [min(cap, math.floor(t / s)) if s else 0 for t, s in zip(target, sizes, strict=True)]
    extra = [max(0, min(s, round(t - f * s))) if f < cap else 0 for t, f, s in zip(target, full, sizes, strict=True)]
    base = spark.createDataFrame(
        [(k, r.source, sizes[k], float(target[k]), n_blocks[k], full[k], extra[k]) for k, r in enumerate(found)],
        "_no int, _source string, _source_size long, _target double, _blocks int, _full int, _extra long",
    )
    small = F.broadcast(base) if len(found) <= MAX_BROADCAST_SOURCES else base
    keyed = digest.join(small, digest["source"].eqNullSafe(F.col("_source"))).withColumn("block", _block("hash", "_blocks"))
    # at most MAX_BLOCKS rows a source
    blocks = materialise(keyed.groupBy("_no", "_full", "_extra", "block").agg(F.sum("size").alias("words")), "mix-blocks")
    for e in range(cap + 1):
        blocks = blocks.withColumn(f"rank{e}", F.row_number().over(Window.partitionBy("_no").orderBy(_order("block", F.lit(e), seed), "block")) - 1)
    blocks = blocks.withColumn("order", _order("block", F.col("_full"), seed))
    until = F.sum("words").over(Window.partitionBy("_no").orderBy("order", "block"))
    cut = blocks.withColumn("until", until).filter((F.col("until") >= F.col("_extra")) & (F.col("_extra") > 0))
    cut = cut.groupBy("_no").agg(F.min_by(F.struct("block", "order", (F.col("until") - F.col("words")).alias("before")), F.struct("until", "order")).alias("c"))
    cut = cut.select("_no", "c.*").cache()
    # inside the one block of a source that is taken in part: documents in hash order
    one = F.broadcast(cut) if len(found) <= MAX_BROADCAST_SOURCES else cut
    part = keyed.join(one, ["_no", "block"]).groupBy("_no", "_extra", "before", "hash").agg(F.sum("size").alias("w"), F.count(F.lit(1)).alias("n"))
    part = part.withColumn("until", F.col("before") + F.sum("w").over(Window.partitionBy("_no").orderBy("hash")))
    last = part.filter(F.col("until") >= F.col("_extra")).groupBy("_no").agg(F.min_by(F.struct("hash", "n", (F.col("_extra") - F.col("until") + F.col("w")).alias("left")), "until").alias("l"))
    edge = {r["_no"]: r for r in cut.join(last.select("_no", F.col("l.hash").alias("hash"), F.col("l.n").alias("n"), F.col("l.left").alias("left")), "_no").collect()}
    cut.unpersist()
    used = {r["_no"]: r["n"] for r in blocks.join(F.broadcast(spark.createDataFrame([(k, r["order"]) for k, r in edge.items()], "_no int, edge long")), "_no").filter("order <= edge").groupBy("_no").agg(F.count(F.lit(1)).alias("n")).collect()} if edge else {}
    draws = [full[k] * n_blocks[k] + used.get(k, 0) for k in range(len(found))]
    quotas = splitting_tree(draws, n_shards, seed)
    rows = []
    for k, r in enumerate(found):
        e = edge.get(k)
        rows.append((k, r.source, sizes[k], float(target[k]), n_blocks[k], full[k], e["order"] if e else None, e["block"] if e else None, e["hash"] if e else None, int(e["left"]) // int(e["n"]) if e else None, [int(x) for x in np.cumsum(quotas[k])]))
    table = spark.createDataFrame(rows, "_no int, _source string, _source_size long, _target double, _blocks int, _full int, _edge_order long, _edge_block int, _edge_hash long, _edge_words long, _bounds array<long>")
    return Plan(table, blocks.select("_no", "block", *(f"rank{e}" for e in range(cap + 1))), len(found), sum(n_blocks), sum(int(r.rows) for r in found), seed)


def _decide(frame: DataFrame, plan: Plan, source: str, doc_hash: str) -> DataFrame:
    """Adds the plan's columns, ``_block``, ``_part`` (2: whole block, 1: edge document, 0: none) and ``_in`` (draws)."""
    joined = frame.join(plan.table, F.col(source).eqNullSafe(F.col("_source")))
    joined = joined.withColumn("_block", _block(doc_hash, "_blocks")).withColumn("_at", _order("_block", F.col("_full"), plan.seed))
    edge_block = (F.col("_at") == F.col("_edge_order")) & (F.col("_block") == F.col("_edge_block"))
    whole = F.coalesce((F.col("_at") < F.col("_edge_order")) | (edge_block & (F.col(doc_hash) < F.col("_edge_hash"))), F.lit(False))
    edge = F.coalesce(edge_block & (F.col(doc_hash) == F.col("_edge_hash")), F.lit(False))
    return joined.withColumn("_part", F.when(whole, 2).when(edge, 1).otherwise(0))


def _shards(plan: Plan, cap: int) -> Column:
    """The shard of each of a row's ``_copies``: that of its block's draw in each round."""
    ranks = F.array(*(F.col(f"rank{e}") for e in range(cap + 1)))
    places = F.transform(F.slice(ranks, 1, F.col("_copies")), lambda r, e: e * F.col("_blocks") + r)
    return F.transform(places, lambda p: F.size(F.filter(F.col("_bounds"), lambda b: b <= p)))


def _digest(docs: DataFrame, id_col: str, text_col: str, source_col: str, seed: int, *more: Column) -> DataFrame:
    slim = docs.select(F.col(source_col).cast("string").alias("source"), _document_hash(id_col, text_col, seed).alias("hash"), *more, F.col(text_col).alias("text"))
    return word_sizes(slim, "text", "size")


def mix(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: Sequence[float] = (5, 2, 1), cap: int = 3, n_shards: int = 8, seed: int = 20) -> DataFrame:
    """One row per document row: id, source, size, source_size, target, taken (words), copies
    (rounds it takes part in, the edge document's part counted), shards (the shard of each
    round) and shuffle_key (order inside a shard)."""
    digest = materialise(_digest(docs, id_col, text_col, source_col, seed, F.col(id_col).alias("id")), "mix-digest")
    plan = make_plan(digest.drop("id"), weights=weights, cap=cap, n_shards=n_shards, seed=seed)
    out = _decide(digest, plan, "source", "hash")
    extra = F.when(F.col("_part") == 2, F.col("size")).when(F.col("_part") == 1, F.least("size", "_edge_words")).otherwise(0)
    blocks = plan.blocks.withColumnsRenamed({"_no": "_b_no", "block": "_b_block"})
    out = out.join(blocks, (F.col("_no") == F.col("_b_no")) & (F.col("_block") == F.col("_b_block")), "left")
    out = out.withColumn("_copies", (F.col("_full") + F.when(F.col("_part") > 0, 1).otherwise(0)).cast("int"))
    return out.select(
        F.col("id").alias(id_col),
        F.col("source").alias(source_col) if source_col != id_col else F.col("source"),
        "size",
        F.col("_source_size").alias("source_size"),
        F.col("_target").alias("target"),
        (F.col("_full") * F.col("size") + extra).cast("long").alias("taken"),
        F.col("_copies").alias("copies"),
        _shards(plan, cap).alias("shards"),
        F.xxhash64(F.lit(seed + 1), F.col("hash")).alias("shuffle_key"),
    )


def mixed_documents(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: Sequence[float] = (5, 2, 1), cap: int = 3, n_shards: int = 8, seed: int = 20) -> DataFrame:
    """The mix itself: each row of ``docs`` as often as it is taken (the edge document whole when any
    of it is), with the columns of ``docs`` and no others.

    Every copy goes to the output shard that the splitting tree gave its block's draw, and stands
    there in the order of its shuffle key: the rows are dealt by shard and part of a shard (partition
    ``shard * parts + part`` of the result), and sorted inside.  A shard has about one part in ``PART_ROWS`` rows, so no task holds a shard.
    """
    digest = materialise(_digest(docs, id_col, text_col, source_col, seed), "mix-digest")
    plan = make_plan(digest, weights=weights, cap=cap, n_shards=n_shards, seed=seed)
    inner = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), F.col(source_col).cast("string").alias("_doc_source"), _document_hash(id_col, text_col, seed).alias("_hash"))
    out = _decide(inner, plan, "_doc_source", "_hash")
    taken = F.when(F.col("_part") == 2, 1).when((F.col("_part") == 1) & (F.col("_edge_words") > 0), 1).otherwise(0)
    out = out.withColumn("_copies", (F.col("_full") + taken).cast("int")).filter("_copies > 0")
    blocks = plan.blocks.withColumnsRenamed({"_no": "_b_no", "block": "_b_block"})
    out = out.join(F.broadcast(blocks) if plan.n_blocks <= MAX_BROADCAST_SOURCES else blocks, (F.col("_no") == F.col("_b_no")) & (F.col("_block") == F.col("_b_block")), "left")
    out = out.withColumn("_shards", _shards(plan, cap)).select("_row", F.posexplode("_shards").alias("_round", "_shard"), F.col("_hash"))
    out = out.withColumn("_shuffle", F.xxhash64(F.lit(seed + 1), "_hash", "_round"))
    parts = max(1, -(-plan.rows * cap // (n_shards * PART_ROWS)))
    out = out.withColumn("_piece", F.pmod(F.col("_shuffle"), F.lit(parts)))
    place = (F.col("_shard") * parts + F.col("_piece")).cast("int")
    return out.repartitionById(n_shards * parts, place).sortWithinPartitions("_shuffle").select("_row.*")
