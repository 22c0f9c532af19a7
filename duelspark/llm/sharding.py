"""Sharding by balanced label propagation.

Linked documents (in the query: equal texts, each linked with the first of its group) should share a shard, and shards hold
counts at most one apart. Labels begin with a hash of each node's own id, which knows nothing of the links. In every round a
join and an aggregation count each node's neighbours by shard; nodes move towards the shard that holds most of them, as far as
quotas allow. Even rounds listen to neighbours of smaller ids and odd rounds to those of greater ids, so that the two ends of
a link do not change places for ever. Rows that two shards exchange are admitted, and beyond these a share that fits into the
room of a shard, chosen by a hash; groups above a quota get only the room that smaller ones leave.
At last the counts are made exact: rows are ranked within their shard, groups up to a quota first and each in a run of its own,
then those above a quota, unlinked rows last; those beyond the quota fill the gaps of the other shards.

Ranks come from counts of hashed parts, so no task sorts a whole shard. Only counts per shard (and per shard and part)
reach the driver. A group larger than a shard must be cut; a smaller one is cut by levelling only where a run crosses the end of
its shard's quota or of the gap that it fills. No row is dropped for it.

Defined results: null texts count as empty; repeated rows are rows of their own; with fewer rows than shards some shards are
empty; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import join_hot, materialise, unmaterialise

PARTS, PART_ROWS = 64, 100_000
HOT = 1000  # a key that more than this part of all rows have is hot


def propagate(nodes: DataFrame, links: DataFrame, shards: int, rounds: int = 4, slack: float = 0.02) -> DataFrame:
    """nodes (id), links (a, b) -> id, shard, lead (smallest of a node and its neighbours, null if unlinked), size (of the lead's group, null for small ones)."""
    both = materialise(links.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(links.select(F.col("b").alias("u"), F.col("a").alias("v"))).where("u <> v"), "links")
    quota = nodes.count() / shards
    hubs = materialise(both.groupBy("v").agg(F.count("*").alias("n")).where(F.col("n") > max(100, both.count() // HOT)).select("v"), "hubs")  # fewer than HOT
    seeds = both.groupBy("u").agg(F.min("v").alias("v"))
    start = nodes.join(seeds, nodes["id"] == seeds["u"], "left").select("id", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int").alias("shard"), F.least("u", "v").alias("lead"))
    start = materialise(start.withColumn("lead", F.when(F.col("lead").isNotNull(), F.least("id", "lead"))), "labels")
    sizes = start.where("lead IS NOT NULL").groupBy("lead").agg(F.count("*").alias("size")).where(F.col("size") > min(quota, PART_ROWS))  # few: at most a row for each quota or PART_ROWS records
    labels = materialise(start.join(F.broadcast(sizes), "lead", "left").select("id", "shard", "lead", "size"), "labels")
    unmaterialise(start)
    wide = (F.coalesce("size", F.lit(0)) > quota).cast("int")
    for turn in range(rounds):
        load = {(r["shard"], r["wide"]): r["n"] for r in labels.where("lead IS NOT NULL").groupBy("shard", wide.alias("wide")).agg(F.count("*").alias("n")).collect()}
        heard = F.col("v") < F.col("u") if turn % 2 == 0 else F.col("v") > F.col("u")
        of = labels.select(F.col("id").alias("v"), F.col("shard").alias("to"))
        votes = join_hot(both, of, ["v"], of.join(F.broadcast(hubs), "v", "left_semi"), F.col("u")).groupBy("u", "to").agg(F.sum(heard.cast("int")).alias("gain"), F.count("*").alias("all"))
        mine = votes.join(labels.select(F.col("id").alias("u"), "shard", wide.alias("wide")), "u")
        wish = mine.groupBy("u", "shard", "wide").agg(F.max(F.when(F.col("to") != F.col("shard"), F.struct("gain", (-F.col("to")).alias("to")))).alias("m"), F.coalesce(F.max(F.when(F.col("to") == F.col("shard"), F.col("all"))), F.lit(0)).alias("kept"))
        moves = materialise(wish.where("m.gain > kept").select("u", "shard", "wide", (-F.col("m.to")).alias("to")), "moves")
        asked = {(r["shard"], r["to"], r["wide"]): r["n"] for r in moves.groupBy("shard", "to", "wide").agg(F.count("*").alias("n")).collect()}
        shares = admit(asked, load, shards, quota * (1 + slack))
        at = (F.col("shard") * shards + F.col("to")) * 2 + F.col("wide")
        admitted = F.get(F.split(F.lit(",".join(map(str, shares))), ",").cast("array<int>"), at)
        moved = moves.where(F.pmod(F.xxhash64("u", F.lit(turn)), F.lit(1_000_000)) < admitted).select("u", "to")
        old, labels = labels, materialise(labels.join(moved, labels["id"] == moved["u"], "left").select("id", F.coalesce("to", "shard").alias("shard"), "lead", "size"), "labels")
        unmaterialise(old)
        unmaterialise(moves)
    unmaterialise(both)
    unmaterialise(hubs)
    return labels


def admit(asked: dict[tuple[int, int, int], int], load: dict[tuple[int, int], int], shards: int, quota: float) -> list[int]:
    """Millionths of the rows to admit, by (from, to, wide): what two shards exchange, and what fits into the room left.

    Only linked rows fill a quota, as levelling sends unlinked ones away first; groups above a quota take what the others leave.
    """
    shares, filled = [0] * (shards * shards * 2), [0.0] * shards
    for wide in (0, 1):
        fair = {(s, to): min(n, asked.get((to, s, wide), 0)) for (s, to, w), n in asked.items() if w == wide}
        beyond = [0] * shards
        for (s, to), n in fair.items():
            beyond[to] += asked[s, to, wide] - n
        for to in range(shards):
            filled[to] += load.get((to, wide), 0)
        room = [max(0.0, quota - filled[to]) for to in range(shards)]
        for (s, to), n in fair.items():
            more = (asked[s, to, wide] - n) * min(1.0, room[to] / beyond[to]) if beyond[to] else 0.0
            shares[(s * shards + to) * 2 + wide] = int(1_000_000 * (n + more) / asked[s, to, wide])
            filled[to], filled[s] = filled[to] + more, filled[s] - more
    return shares


def level(labels: DataFrame, shards: int) -> DataFrame:
    """id, shard, slot: counts at most one apart, slots without gaps from 0.

    Rows are ranked within their shard by tier: groups of at most PART_ROWS, greater ones, those above a quota, unlinked rows.
    """
    n = labels.count()
    parts = max(PARTS, -(-n // (shards * PART_ROWS)))
    size, part_rows = F.coalesce("size", F.lit(0)), min(PART_ROWS, max(256, n // (shards * PARTS)))
    tier = F.when(F.col("lead").isNull(), 3).when(size > n / shards, 2).when(size > PART_ROWS, 1).otherwise(0)
    dealt = lambda c, key: F.pmod(F.xxhash64(c, F.lit(key)), F.lit(parts))
    tiers = labels.withColumn("tier", tier).withColumn("part", F.when(F.col("tier") == 3, dealt("id", "part")).when(F.col("tier") == 0, dealt("lead", "part")).otherwise(F.col("lead")))
    piece = F.when(F.col("tier").isin(1, 2), F.pmod(F.xxhash64("id", F.lit("piece")), F.ceil(size / part_rows))).otherwise(F.lit(0))
    parted, key = tiers.withColumn("piece", piece), ["shard", "tier", "part", "piece"]
    counts = parted.groupBy(*key).agg(F.count("*").alias("n"))  # a row for about part_rows records, and 2 x PARTS x shards at least
    before = counts.select(*key, (F.sum("n").over(W.partitionBy("shard").orderBy("tier", "part", "piece").rowsBetween(W.unboundedPreceding, 0)) - F.col("n")).alias("before"))
    ranked = parted.withColumn("within", F.row_number().over(W.partitionBy(*key).orderBy("lead", "id"))).join(F.broadcast(before), key).withColumn("rank", F.col("before") + F.col("within") - 1)
    load = {r["shard"]: r["n"] for r in counts.groupBy("shard").agg(F.sum("n").alias("n")).collect()}
    total = sum(load.values())
    quota = [total // shards + (s < total % shards) for s in range(shards)]
    kept = [min(load.get(s, 0), quota[s]) for s in range(shards)]
    extra, gap = [0], [0]
    for s in range(shards):
        extra.append(extra[-1] + load.get(s, 0) - kept[s])
        gap.append(gap[-1] + quota[s] - kept[s])
    pick = lambda values, at: F.get(F.array(*(F.lit(int(v)).cast("long") for v in values)), at)
    beyond = F.col("rank") - pick(quota, F.col("shard"))
    queue = pick(extra, F.col("shard")) + beyond
    to = F.size(F.filter(F.array(*(F.lit(int(v)).cast("long") for v in gap[1:])), lambda end: end <= F.col("queue")))
    placed = ranked.withColumn("queue", F.when(beyond >= 0, queue)).withColumn("to", F.when(F.col("queue").isNotNull(), to))
    return placed.select("id", F.coalesce("to", "shard").alias("shard"), F.when(F.col("to").isNotNull(), pick(kept, F.col("to")) + F.col("queue") - pick(gap, F.col("to"))).otherwise(F.col("rank")).cast("long").alias("slot"))


def shard_texts(documents: DataFrame, shards: int = 24, rounds: int = 4) -> DataFrame:
    """doc_id, size, text_crc32, law (`rows`), shard, slot, grown_shard (null under this law)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("same"), F.monotonically_increasing_id().alias("id"))
    nodes = materialise(rows, "nodes")  # ids are fixed by being written
    key = ["same", "size", "text_crc32"]
    first = materialise(nodes.groupBy(*key).agg(F.min("id").alias("b"), F.count("*").alias("n")).where("n > 1"), "firsts")
    hot = first.where(F.col("n") > max(100, nodes.count() // HOT)).drop("n")  # fewer than HOT texts
    links = join_hot(nodes, first.drop("n"), key, hot, F.col("id")).where("id <> b").select(F.col("id").alias("a"), "b")
    labels = propagate(nodes.select("id"), links, shards, rounds)
    unmaterialise(first)
    placed = level(labels, shards)
    return nodes.join(placed, "id").select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def cut_links(placed: DataFrame, links: DataFrame) -> int:
    """Links whose ends are in different shards."""
    of = lambda c: placed.select(F.col("id").alias(c), F.col("shard").alias(f"shard_{c}"))
    return links.join(of("a"), "a").join(of("b"), "b").where("shard_a <> shard_b").count()
