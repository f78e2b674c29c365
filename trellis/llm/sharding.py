"""Sharding on a consistent-hash ring with virtual nodes and bounded loads.

Every shard owns `points` arcs of the ring; a key belongs to the shard that owns its arc and,
where that shard is full, continues clockwise to the next one with room. Capacities sum to
exactly the number of rows (the first n mod m shards take one row more), so counts are at most
one apart: the law is `rows`. Movement stays limited because every key below its shard's
capacity keeps its ring owner.

How much overflows depends on the counts by arc alone. These are at most shards x points numbers,
which the driver plays through once; rows then find their shard from their rank in their arc. A
row's rank follows from a hash of the row itself, so where it goes doesn't depend on how the table
is split into files or tasks. No shard's, arc's or key's rows are ever gathered in one task:
ranks are summed from counts by arc, by a part of the hashes, and by hash and task.

Nulls: a null key has an arc of its own hash, a null text has no bytes (size 8). Repeated rows
(ties) each take a place of their own, and as they are equal it doesn't matter which takes which.
Texts have any length. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checkpointed

#: Largest ring that may be planned on the driver and broadcast.
MOST_POINTS = 1 << 20
RING = 1 << 32
#: Parts of an arc's hashes within which rows are ranked.
SUBS = 256


def ring(shards: int, points: int = 256, salt: str = "ring") -> list[tuple[int, int]]:
    """(position, shard) of every virtual node, clockwise."""
    if not 0 < shards * points <= MOST_POINTS:
        raise ValueError(f"1 to {MOST_POINTS} virtual nodes are supported")
    place = lambda s, k: int.from_bytes(hashlib.blake2b(f"{salt}/{s}/{k}".encode(), digest_size=4).digest(), "big")
    return sorted({place(s, k): s for s in reversed(range(shards)) for k in range(points)}.items())


def arc_of(nodes: list[tuple[int, int]], position: int) -> int:
    """Index of the node that owns a position: the first at or after it, clockwise."""
    return bisect_left(nodes, (position, -1)) % len(nodes)


def plan(nodes: list[tuple[int, int]], counts: dict[int, int], capacity: list[int]) -> list[tuple[int, int, int, int, int]]:
    """(arc, first rank, past-the-last rank, shard, first slot) for the rows of every arc.

    Arcs fill their own shards first, all of them, so that a key moves only when its owner is
    full; overflow then continues clockwise from its arc. Capacities must sum to the rows.
    """
    room, used, out, over = list(capacity), [0] * len(capacity), [], []

    def take(arc: int, at: int, n: int, shard: int) -> int:
        k = min(n, room[shard])
        if k:
            out.append((arc, at, at + k, shard, used[shard]))
            room[shard] -= k
            used[shard] += k
        return k

    for arc in sorted(counts):
        k = take(arc, 0, counts[arc], nodes[arc][1])
        if k < counts[arc]:
            over.append((arc, k, counts[arc]))
    for arc, at, end in over:
        step = arc
        while at < end:
            step = (step + 1) % len(nodes)
            at += take(arc, at, end - at, nodes[step][1])
            if step == arc and at < end:
                raise ValueError("capacities don't cover all rows")
    return out


def capacities(rows: int, shards: int, slack: float = 0.0) -> list[int]:
    """Row bounds by shard: exactly balanced without slack, else (1 + slack) times the mean, rounded up."""
    if slack <= 0:
        return [rows // shards + (s < rows % shards) for s in range(shards)]
    return [int(-(-rows * (1 + slack) // shards))] * shards


def assign(spark: SparkSession, rows: DataFrame, key: str, shards: int = 24, points: int = 256, slack: float = 0.0) -> DataFrame:
    """Add `shard` and `slot` (gapless from 0 within a shard) to the rows."""
    nodes = ring(shards, points)
    # the owner's index, by binary search in a constant array of positions: a sorted array of at most MOST_POINTS longs
    positions = F.split(F.lit(",".join(str(p) for p, _ in nodes)), ",").cast("array<bigint>")
    place = F.pmod(F.xxhash64(F.lit("key"), F.col(key)), F.lit(RING))
    # every row's arc: the count of nodes before its place, found in a bucket table over the ring's upper bits
    marked = rows.withColumn("__place", place)
    width = max(1, RING // 4096)
    starts = [arc_of(nodes, b * width) if b * width <= nodes[-1][0] else len(nodes) for b in range(RING // width)]
    first = F.split(F.lit(",".join(map(str, starts))), ",").cast("array<int>")
    begin = F.element_at(first, (F.floor(F.col("__place") / width) + 1).cast("int"))
    near = F.slice(positions, begin + 1, F.lit(_most_in_a_bucket(nodes, width) + 1))
    marked = marked.withColumn("__arc", F.pmod(begin + F.size(F.filter(near, lambda p: p < F.col("__place"))), F.lit(len(nodes))).cast("int")).drop("__place")
    whole = [F.col(f"`{c}`") for c, kind in rows.dtypes if not kind.startswith("map")]
    marked = marked.withColumn("__digest", F.struct(F.xxhash64(F.lit("rank"), *whole).alias("a"), F.hash(F.lit("rank"), *whole).alias("b")))
    marked = checkpointed(marked.withColumn("__id", F.monotonically_increasing_id()).withColumn("__part", F.shiftright("__id", 33).cast("int")))
    same = ["__part", "__arc", "__digest"]
    local = marked.withColumn("__local", F.row_number().over(Window.partitionBy(*same).orderBy("__id")) - 1)
    counts = {r["__arc"]: r["n"] for r in marked.groupBy("__arc").agg(F.count("*").alias("n")).collect()}
    pieces = plan(nodes, counts, capacities(sum(counts.values()), shards, slack))
    by_arc: dict[int, list] = {}
    for arc, lo, hi, shard, slot in pieces:
        by_arc.setdefault(arc, []).append((lo, hi, shard, slot))
    lookup = spark.createDataFrame([(a, x) for a, x in by_arc.items()], "__arc int, __pieces array<struct<lo: bigint, hi: bigint, shard: int, slot: bigint>>")
    before = lambda over: F.sum("__n").over(over.rowsBetween(Window.unboundedPreceding, 0)) - F.col("__n")
    some = marked.groupBy(*same).agg(F.count("*").alias("__n")).withColumn("__sub", F.pmod(F.col("__digest.a"), F.lit(SUBS)).cast("int"))
    within = some.withColumn("__base", before(Window.partitionBy("__arc", "__sub").orderBy("__digest", "__part")))
    subs = some.groupBy("__arc", "__sub").agg(F.sum("__n").alias("__n")).withColumn("__start", before(Window.partitionBy("__arc").orderBy("__sub"))).drop("__n")
    base = within.join(subs, ["__arc", "__sub"]).select(*same, (F.col("__base") + F.col("__start")).alias("__base"))
    ranked = local.join(base, same).withColumn("__rank", F.col("__base") + F.col("__local")).join(F.broadcast(lookup), "__arc")
    hit = F.filter("__pieces", lambda p: (p["lo"] <= F.col("__rank")) & (F.col("__rank") < p["hi"]))[0]
    return ranked.withColumn("__hit", hit).withColumn("shard", F.col("__hit.shard")).withColumn("slot", F.col("__hit.slot") + F.col("__rank") - F.col("__hit.lo")).drop("__hit", "__pieces", "__rank", "__local", "__base", "__digest", "__id", "__part", "__arc")


def _most_in_a_bucket(nodes: list[tuple[int, int]], width: int) -> int:
    seen: dict[int, int] = {}
    for p, _ in nodes:
        seen[p // width] = seen.get(p // width, 0) + 1
    return max(seen.values())


def shard_documents(spark: SparkSession, docs: DataFrame, shards: int = 24, points: int = 256) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of `docs` (law `rows`)."""
    text = F.coalesce(F.col("text").cast("binary"), F.lit(b""))
    slim = docs.select("doc_id", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    out = assign(spark, slim, "doc_id", shards, points)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
