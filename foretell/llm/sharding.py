"""Sharding by balanced label propagation, in DataFrame operations only.

Links are given as memberships (node, hub): nodes of one hub belong together, so a group of any
size costs one row per member and never its pairs.  A node is a document row, or with given links
a document id and all its rows.  Nodes start at a hashed shard; in each round a hub counts its
rows by shard (one aggregation), every member sums the counts of its hubs (one join), and wants
the shard with most of its neighbours.  Moves into a shard are let in up to its free capacity and
what leaves it: the driver sees the demand as a table of shards by shards by buckets (of fixed
size) and answers with thresholds.  Documents without links fill what is left,
so that at the end the numbers of rows differ by one at most.

Defined results: a null text has size 1, checksum 0 and no links; empty texts are a group of
their own; rows repeated with one id move together until the last step, which may part them to
keep the counts even; an empty table gives an empty result; a group larger than a shard is
spread over as few shards as have room.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, pick, release, salted_join

ROUNDS = 5
#: Buckets in which demand is told to the driver, and parts of the bucket at the threshold.
BUCKETS, PARTS = 256, 4096
#: Rows a ranking bucket is aimed at, and the number of such buckets at most.
RANK_ROWS, MAX_RANK_BUCKETS = 20_000, 1 << 16


def digest(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, row_no, size, text_crc32, hub (fingerprint of the text, null without one)."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(
        F.col(id_col).alias("id"),
        F.monotonically_increasing_id().alias("row_no"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.when(F.col(text_col).isNotNull(), F.md5(text.cast("binary"))).alias("hub"),
    )


def _memberships(rows: DataFrame, total: int) -> DataFrame:
    """(node, hub, n) of rows: rows of equal text have a hub, and so have rows of one id that are not all of one text."""
    texts = rows.filter("hub is not null").select(F.col("row_no").alias("node"), "hub")
    known = rows.filter("id is not null")
    ids = known.groupBy("id").agg(F.count(F.lit(1)).alias("m"), F.count("hub").alias("_texts"), F.min("hub").alias("_low"), F.max("hub").alias("_high"))
    ids = ids.filter("_texts > 0 and (_texts < m or _low <> _high)").select("id", "m")
    parts = salted_join(known, ids, ["id"], "m", total).select(F.col("row_no").alias("node"), F.concat(F.lit("id "), F.col("id").cast("string")).alias("hub"))
    return texts.unionByName(parts).withColumn("n", F.lit(1).cast("long"))


def _admitted(demand: np.ndarray, load: list[int], cap: list[int]) -> tuple[list[int], list[int]]:
    """For each shard the number of leading buckets let in, and the rows of room left then.

    ``demand[k, w, b]``: rows in shard k that want shard w, in bucket b.  What leaves makes room for
    what comes; from all demand, buckets are taken back until no shard is over its capacity by them.
    """
    n_shards, buckets = len(cap), demand.shape[2]
    until = [buckets] * n_shards
    came = np.concatenate([np.zeros((n_shards, 1), np.int64), demand.sum(axis=0).cumsum(axis=1)], axis=1)  # (want, buckets let in)
    gone = np.concatenate([np.zeros((n_shards, n_shards, 1), np.int64), demand.cumsum(axis=2)], axis=2)
    while True:
        before = list(until)
        room = []
        for k in range(n_shards):
            free = cap[k] - load[k] + sum(int(gone[k, w, until[w]]) for w in range(n_shards))
            until[k] = min(until[k], max(0, int(np.searchsorted(came[k], free, side="right")) - 1))
            room.append(free - int(came[k, until[k]]))
        if until == before:
            return until, room


def propagate(links: DataFrame, total: int, n_shards: int, *, rounds: int = ROUNDS) -> DataFrame | None:
    """(node, shard) of linked nodes.  ``links``: node, hub, n (rows that the node stands for), no
    membership twice; ``total``: rows in all."""
    sizes = links.groupBy("hub").agg(F.count(F.lit(1)).alias("m"), F.sum("n").alias("_rows")).filter("_rows > 1").select("hub", "m")
    linked = materialise(salted_join(links, sizes, ["hub"], "m", total).select("node", "hub", "n"), "shard-links")
    nodes = linked.groupBy("node").agg(F.max("n").alias("n"), F.min("hub").alias("first_hub")).withColumn("shard", F.pmod(F.xxhash64("node"), F.lit(n_shards)).cast("int"))
    nodes = materialise(nodes, "shard-nodes")
    count = linked.count()
    if not count:
        return None
    cap = [total // n_shards + (k < total % n_shards) for k in range(n_shards)]
    here = [f"s{k}" for k in range(n_shards)]
    full = [False] * n_shards
    for r in range(rounds):
        held = dict(nodes.groupBy("shard").agg(F.sum("n")).collect())
        load = [held.get(k, 0) for k in range(n_shards)]
        # a shard that has turned nodes away is wanted again only when it has room
        roomy = [not full[k] or cap[k] - load[k] > cap[k] // 200 for k in range(n_shards)]
        placed = linked.join(nodes.select("node", "shard"), "node")
        counts = placed.groupBy("hub").agg(F.count(F.lit(1)).alias("m"), *[F.sum(F.when(F.col("shard") == k, F.col("n")).otherwise(0)).alias(c) for k, c in enumerate(here)])
        votes = salted_join(placed.select("node", "hub"), counts, ["hub"], "m", count).groupBy("node").agg(*[F.sum(c).alias(c) for c in here])
        turn = F.xxhash64("first_hub")
        score = F.array(*[F.when(F.lit(roomy[k]) | (F.col("shard") == k), F.col(c) * 16 + F.pmod(turn + k, F.lit(n_shards))).otherwise(F.lit(-1)) for k, c in enumerate(here)])
        wanting = nodes.join(votes, "node").withColumn("want", (F.array_position(score, F.array_max(score)) - 1).cast("int"))
        wanting = wanting.withColumn("bucket", F.pmod(F.xxhash64("first_hub", F.lit(r)), F.lit(BUCKETS)).cast("int")).withColumn("part", F.pmod(F.xxhash64("node", F.lit(r)), F.lit(PARTS)).cast("int"))
        wanting = materialise(wanting.select("node", "n", "first_hub", "shard", "want", "bucket", "part"), "shard-wants")
        moving = wanting.filter("want <> shard")
        demand = np.zeros((n_shards, n_shards, BUCKETS), np.int64)
        for shard, want, bucket, n in moving.groupBy("shard", "want", "bucket").agg(F.sum("n")).collect():
            demand[shard, want, bucket] = n
        if not demand.any():
            release(wanting)
            break
        until, room = _admitted(demand, load, cap)
        full = [full[k] or until[k] < BUCKETS for k in range(n_shards)]
        # of the first bucket that does not fit whole, as many parts as fit
        parts = np.zeros((n_shards, PARTS), np.int64)
        for want, part, n in moving.filter(F.col("bucket") == pick(until, F.col("want"))).groupBy("want", "part").agg(F.sum("n")).collect():
            parts[want, part] = n
        share = [int(np.searchsorted(parts[k].cumsum(), room[k], side="right")) if until[k] < BUCKETS else 0 for k in range(n_shards)]
        edge = (F.col("bucket") == pick(until, F.col("want"))) & (F.col("part") < pick(share, F.col("want")))
        moves = (F.col("bucket") < pick(until, F.col("want"))) | edge
        moved = materialise(wanting.withColumn("shard", F.when(moves, F.col("want")).otherwise(F.col("shard"))).select("node", "n", "first_hub", "shard"), "shard-nodes")
        release(nodes, wanting)
        nodes = moved
    return nodes.select("node", "shard")


def _even(rows: DataFrame, labels: DataFrame | None, n_shards: int) -> DataFrame:
    """Every row to a shard and slot with exactly even counts; ``labels`` (node, shard) are kept where they fit."""
    group = F.coalesce(F.col("shard"), F.lit(n_shards))
    rows = rows.join(labels, "node", "left") if labels is not None else rows.withColumn("shard", F.lit(None).cast("int"))
    total = rows.count()
    buckets = min(MAX_RANK_BUCKETS, max(256, total // RANK_ROWS))
    rows = rows.withColumn("_group", group).drop("shard").withColumn("_bucket", F.pmod(F.xxhash64("row_no"), F.lit(buckets)).cast("int"))
    rows = materialise(rows, "shard-rows")
    # at most (n_shards + 1) * MAX_RANK_BUCKETS rows
    counts = rows.groupBy("_group", "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    counts = counts.withColumn("_before", F.sum("_n").over(Window.partitionBy("_group").orderBy("_bucket")) - F.col("_n")).drop("_n")
    load = dict(rows.groupBy("_group").count().collect())
    cap = [total // n_shards + (k < total % n_shards) for k in range(n_shards)]
    kept = [min(cap[k], load.get(k, 0)) for k in range(n_shards)]
    over, spill = [], load.get(n_shards, 0)
    for k in range(n_shards):
        over.append(spill)
        spill += load.get(k, 0) - kept[k]
    first, at = [], 0
    for k in range(n_shards):
        first.append(at)
        at += cap[k] - kept[k]
    place = F.row_number().over(Window.partitionBy("_group", "_bucket").orderBy("row_no")) - 1
    ranked = rows.join(F.broadcast(counts), ["_group", "_bucket"]).withColumn("_rank", F.col("_before") + place)
    mine = F.col("_group") < n_shards
    stays = mine & (F.col("_rank") < pick([*kept, 0], F.col("_group")))
    loose = F.when(mine, pick([*over, 0], F.col("_group")) + F.col("_rank") - pick([*kept, 0], F.col("_group"))).otherwise(F.col("_rank"))
    to = F.aggregate(F.array(*[F.lit(x) for x in first]), F.lit(-1), lambda a, x: F.when(x <= F.col("_loose"), a + 1).otherwise(a))
    ranked = ranked.withColumn("_loose", loose).withColumn("_to", to)
    shard = F.when(stays, F.col("_group")).otherwise(F.col("_to"))
    slot = F.when(stays, F.col("_rank")).otherwise(pick(kept, F.col("_to")) + F.col("_loose") - pick(first, F.col("_to")))
    return ranked.withColumn("shard", shard.cast("int")).withColumn("slot", slot.cast("long")).drop("_group", "_bucket", "_before", "_rank", "_loose", "_to")


def shard_documents(docs: DataFrame, n_shards: int = 8, *, id_col: str = "doc_id", text_col: str = "text", links: DataFrame | None = None, rounds: int = ROUNDS) -> DataFrame:
    """One row per document row: id, size, text_crc32, hub, shard, slot.

    ``links``: memberships (id, hub) of documents; by default rows of equal text are linked, also
    those of one id or of none, and rows of one id.
    """
    rows = materialise(digest(docs, id_col, text_col), "shard-digest")
    total = rows.count()
    if links is None:
        rows, given = rows.withColumn("node", F.col("row_no")), _memberships(rows, total)
    else:
        rows = rows.withColumn("node", F.col("id"))
        weight = rows.filter("node is not null").groupBy("node").agg(F.count(F.lit(1)).alias("n"))
        given = links.select(F.col("id").alias("node"), "hub").dropna().distinct().join(weight, "node")
    labels = propagate(given, total, n_shards, rounds=rounds)
    return _even(rows, labels, n_shards).drop("row_no", "node").withColumnRenamed("id", id_col)


def cut_links(assigned: DataFrame, hub_col: str = "hub", shard_col: str = "shard") -> DataFrame:
    """One row: linked pairs in all, and pairs whose members stand in different shards (by counts, not by pairs)."""
    per = assigned.filter(F.col(hub_col).isNotNull()).groupBy(hub_col, shard_col).agg(F.count(F.lit(1)).alias("c"))
    hubs = per.groupBy(hub_col).agg(F.sum("c").alias("m"), F.sum(F.expr("c * (c - 1) / 2")).alias("inside"))
    return hubs.agg(F.coalesce(F.sum(F.expr("m * (m - 1) / 2")), F.lit(0.0)).alias("pairs"), F.coalesce(F.sum(F.expr("m * (m - 1) / 2 - inside")), F.lit(0.0)).alias("cut_pairs"))
