"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two fingerprints at most `radius` bits apart have a point between them at most half as far from
each. So every distinct fingerprint emits all variants within half the radius (65 for radius 2),
the variants are shuffled, and fingerprints that meet at a variant are linked. For an even radius
such a meeting itself proves the distance: two ways of at most radius/2 make at most radius.
A variant is met by at most as many distinct fingerprints as it has variants itself (65), so no
group grows with the data; each links its members to its least one, never to each other.

`near_duplicates` finds all pairs of a similarity of word shingles, because 64-bit SimHash at a small
radius misses most pairs of similarity 0.8 (they are about 10 bits apart). Its second source of
candidates is exact: two sets of the similarity share one of the first shingles of each in any
common order (`prefix`). Where these meet, nodes are first linked to two members of their group;
then all pairs of a group that no link connects yet are compared too, by sketches that rule a pair
out only with certainty. Candidates are verified on their whole shingle sets. No key's rows are
gathered in one task: groups are pre-aggregated, and rows of hot keys meet a bounded table.

Nulls: a null text is an empty one (fingerprint zero, linked like any other). Null doc_ids are
kept; a class has the least non-null doc_id of its members. Repeated rows share a class.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import KEYS, checkpointed, components, let_go, map_rows, ready, removed, row_batches, row_keys, spread_join, written

SEED = 42


def shingles(text: str | None, n: int) -> list[bytes]:
    """Word n-grams of the text, repeats included; fewer words make one shingle, none make none.

    bytes.lower folds A-Z only and bytes.split cuts at 20 and 09-0D only.
    """
    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return []
    return list(map(b" ".join, zip(*[w[k:] for k in range(n)], strict=False))) if len(w) >= n else [b" ".join(w)]


def hashes(parts: list[bytes]) -> np.ndarray:
    h = xxhash.xxh64_intdigest
    return np.fromiter((h(x, SEED) for x in parts), np.uint64, len(parts))


def fingerprint(h: np.ndarray) -> int:
    """Bit k is 1 if set in over half of the hashes."""
    if not len(h):
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, len(h), 65536):  # whole texts, in steps of bounded memory
        ones += np.unpackbits(h[at : at + 65536].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<u8")[0])


def ball(radius: int, bits: int = 64) -> list[int]:
    """All masks of at most `radius` set bits, as signed longs."""
    out = [sum(1 << b for b in c) for k in range(radius + 1) for c in combinations(range(bits), k)]
    return [m - (1 << 64) if m >> 63 else m for m in out]


def fingerprints(docs: DataFrame, n: int) -> DataFrame:
    """(doc_id, fp): the SimHash of every row's whole text, as a signed long."""

    def work(batch: pa.RecordBatch) -> dict:
        fps = [fingerprint(hashes(shingles(t, n))) for t in batch.column("text").to_pylist()]
        return {"doc_id": batch.column("doc_id"), "fp": np.array(fps, np.uint64).view(np.int64)}

    return map_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), work, "doc_id long, fp long")


def ball_links(distinct: DataFrame, radius: int) -> DataFrame:
    """Edges (a, b) that connect all distinct fingerprints `fp` within an even radius."""
    if radius % 2 or radius < 0:
        raise ValueError("an even radius is needed: a meeting then proves the distance")
    masks = ball(radius // 2)
    near = distinct.select("fp", F.explode(F.transform(F.split(F.lit(",".join(map(str, masks))), ",").cast("array<bigint>"), lambda m: m.bitwiseXOR(F.col("fp")))).alias("v"))
    low = F.first("fp").over(Window.partitionBy("v").orderBy("fp"))
    return near.select("fp", low.alias("low")).where("fp != low").select(F.col("fp").alias("a"), F.col("low").alias("b")).distinct()


def classes(rows: DataFrame, links: DataFrame, node: str) -> DataFrame:
    """(node, class, component_id) of every distinct node: its root, and the least doc_id that links reach."""
    own = rows.groupBy(node).agg(F.min("doc_id").alias("__own"))
    roots = components(links).withColumnRenamed("node", node)
    rooted = own.join(roots, node, "left").withColumn("root", F.coalesce("root", node))
    least = rooted.groupBy("root").agg(F.min("__own").alias("component_id"))
    return checkpointed(rooted.join(least, "root").select(node, F.col("root").alias("class"), "component_id"))


def simhash_classes(docs: DataFrame, n: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fingerprint (hex), component_id for every row: one class for each component of links."""
    rows = checkpointed(fingerprints(docs, n))
    named = classes(rows, ball_links(rows.select("fp").distinct(), radius), "fp")
    return spread_join(rows, named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


# --- a similarity of shingle sets -------------------------------------------------------------------

#: Cells of the histogram of shingles, which is gathered at the driver.
CELLS = 1 << 18
#: Shingles of a prefix whose groups are linked to two of their members before all others are compared.
FIRST = 8
#: Members of a group that are compared with each other in one block.
BLOCK = 2048
#: Members from which a group's classes are bridged before all of them are compared.
BRIDGED = 16
#: Parts that a step is worked off in at most, and rows or bytes from which another is worth its jobs.
PORTIONS, PORTION_ROWS, PORTION_BYTES = 8, 1 << 20, 32 << 20
#: Longs of a sketch.
SKETCH = 16


def common_cells(docs: DataFrame, n: int) -> np.ndarray:
    """Rough counts of shingle hashes by their remainder, for an order with the rare ones first.

    A task reports the cells that stand out among its own. No result depends on these counts: a
    prefix may follow any order, and a good one only keeps groups small.
    """
    types = pa.schema([("k", pa.int32()), ("n", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CELLS, np.int64)
        for part in row_batches(batches):
            some = [np.zeros(0, np.int64)]
            for t in part.column(0).to_pylist():
                h = hashes(shingles(t, n))
                some.append((h % np.uint64(CELLS)).astype(np.int64))
            total += np.bincount(np.concatenate(some), minlength=CELLS)
        k = np.flatnonzero(total > 1 + 2 * total.mean())
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(total[k], pa.int64())], schema=types)

    ready(docs.sparkSession)
    out = np.zeros(CELLS, np.int64)
    for r in docs.select("text").mapInArrow(run, "k int, n long").groupBy("k").agg(F.sum("n").alias("n")).collect():
        out[r["k"]] = r["n"]
    return out


def prefix(own: np.ndarray, common: np.ndarray, similarity: float) -> list[int]:
    """The hashes, as signed longs, of the first shingles of a set by commonness.

    A set of m has `similarity` only with sets that hold at least similarity * m of it, so all but
    the last of so many must be looked at.
    """
    first = len(own) - math.ceil(similarity * len(own)) + 1
    order = np.lexsort((own, common[(own % np.uint64(CELLS)).astype(np.int64)]))
    return list(dict.fromkeys(own[order[:first]].view(np.int64).tolist()))


def sketch(own: np.ndarray, longs: int = SKETCH) -> list[int]:
    """Parities of a set by hash remainder, as signed longs.

    What two sets share cancels out, so their sketches differ in at most as many bits as the sets
    differ in shingles, whatever the hashes are: a test on sketches loses no pair.
    """
    odd = np.bincount((own >> np.uint64(40)).astype(np.int64) % (64 * longs), minlength=64 * longs) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8").tolist()


def fine(own: np.ndarray) -> list[int] | None:
    """A sketch with two bits or more for each shingle of a large set; none where `SKETCH` has as many."""
    longs = 1 << max(0, (2 * len(own) - 1).bit_length() - 6)
    return sketch(own, longs) if longs > SKETCH else None


def may_be_similar_finely(similarity: float, size_a: Column, fine_a: Column, size_b: Column, fine_b: Column) -> Column:
    """The same by fine sketches; the longer, of twice the other's length, is folded onto it."""
    n = F.least(F.size(fine_a), F.size(fine_b))
    apart = lambda x, y: x.bitwiseXOR(y)
    fold = lambda x: F.when(F.size(x) > n, F.zip_with(F.slice(x, 1, n), F.slice(x, n + 1, n), apart)).otherwise(x)
    bits = F.aggregate(F.zip_with(fold(fine_a), fold(fine_b), lambda x, y: F.bit_count(apart(x, y))), F.lit(0), lambda s, x: s + x)
    return fine_a.isNull() | fine_b.isNull() | (bits <= F.lit((1 - similarity) / (1 + similarity) + 1e-9) * (size_a + size_b))


def may_be_similar(similarity: float, size_a: Column, sketch_a: Column, size_b: Column, sketch_b: Column) -> Column:
    """Whether sizes and sketches leave room for the similarity.

    Sets of similarity t differ in at most (1 - t) / (1 + t) of their sizes' sum.
    """
    apart = sum((F.bit_count(F.get(sketch_a, k).bitwiseXOR(F.get(sketch_b, k))) for k in range(1, SKETCH)), F.bit_count(F.get(sketch_a, 0).bitwiseXOR(F.get(sketch_b, 0))))
    alike = F.least(size_a, size_b) >= F.lit(float(similarity)) * F.greatest(size_a, size_b)
    return alike & (apart <= F.lit((1 - similarity) / (1 + similarity) + 1e-9) * (size_a + size_b))


def node_of(text: str | None) -> bytes:
    """Name of a text's words: texts of equal words, but for A-Z's case and spacing, are one node."""
    return xxhash.xxh3_128_digest(b" ".join((text or "").encode("utf-8", "surrogatepass").lower().split()))


def sketches(docs: DataFrame, n: int, keys: list[str], similarity: float) -> DataFrame:
    """The key columns (longs), doc_id, node, fp, number of shingles, sketch and prefix of every row."""
    common = common_cells(docs, n)

    def work(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {"node": [], "fp": [], "size": [], "sketch": [], "fine": [], "prefix": []}
        for t in batch.column("text").to_pylist():
            parts = shingles(t, n)
            h = hashes(parts)
            distinct = set(parts)
            own = np.unique(h)
            if len(own) < len(distinct):  # shingles of one hash count each, so they cost no pair
                own = np.sort(hashes(list(distinct)))
            for c, x in zip(out, (node_of(t), fingerprint(h), len(own), sketch(own), fine(own), prefix(own, common, similarity)), strict=True):
                out[c].append(x)
        return {k: batch.column(k) for k in (*keys, "doc_id")} | out | {"fp": np.array(out["fp"], np.uint64).view(np.int64)}

    given = docs.select(*keys, F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_rows(given, work, ", ".join([*(f"{k} long" for k in keys), "doc_id long, node binary, fp long, size int, sketch array<long>, fine array<long>, prefix array<long>"]))


def ordered(pairs: DataFrame) -> DataFrame:
    """Distinct pairs (a, b) with a < b."""
    return pairs.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def ball_pairs(nodes: DataFrame, radius: int) -> DataFrame:
    """Pairs of nodes whose fingerprints are equal, or meet in a ball: each with its fingerprint's first node."""
    first = nodes.groupBy("fp").agg(F.min("id").alias("a"))
    equal = spread_join(nodes.select("fp", "id"), first, "fp").select("a", F.col("id").alias("b"))
    links = ball_links(first.select("fp"), radius)
    met = links.join(first.select(F.col("fp").alias("a"), F.col("a").alias("x")), "a").join(first.select(F.col("fp").alias("b"), F.col("a").alias("y")), "b")
    return ordered(equal.union(met.select(F.col("x").alias("a"), F.col("y").alias("b"))))


def star_pairs(nodes: DataFrame, similarity: float) -> DataFrame:
    """Pairs that sketches allow, of each node with two members of each group of one of its first shingles.

    The two are chosen by a hash for each group anew, so pairs grow with the nodes and not with the
    square of a group, and a text that is unlike the rest costs a group nothing.
    """
    rows = nodes.select("id", F.explode(F.slice("prefix", 1, FIRST)).alias("key"))
    of = rows.groupBy("key").agg(*[end(F.struct(F.xxhash64("key", "id").alias("rank"), "id")).alias(c) for end, c in ((F.min, "lo"), (F.max, "hi"))], F.count("*").alias("n"))
    ends = written(of.where("lo.id != hi.id").select("key", "n", F.array("lo.id", "hi.id").alias("ends")))
    met = spread_join(rows, ends.select("key", "ends"), "key", ends)
    return allowed(ordered(met.select(F.col("id").alias("a"), F.explode("ends").alias("b"))), nodes, similarity)


def allowed(pairs: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """The pairs of nodes that sizes and sketches allow."""
    for side in "ab":
        pairs = pairs.join(nodes.select(F.col("id").alias(side), F.struct("size", "sketch", "fine").alias(f"of_{side}")), side)
    roughly, finely = (test(similarity, F.col("of_a.size"), F.col(f"of_a.{c}"), F.col("of_b.size"), F.col(f"of_b.{c}")) for test, c in ((may_be_similar, "sketch"), (may_be_similar_finely, "fine")))
    return pairs.where(roughly & finely).select("a", "b")


def portions(total: int | None, each: int) -> int:
    """Parts that a step of so many rows or bytes is worked off in: the shuffle files of one are there at a time."""
    return min(PORTIONS, max(1, math.ceil((total or 0) / each)))


def divided(nodes: DataFrame, links: DataFrame) -> DataFrame:
    """(key, id, root, n) for each of the keys of nodes (id, keys) whose group holds several classes of the links; n: the group's rows."""
    roots = components(links).withColumnRenamed("node", "id")
    parts = portions(nodes.agg(F.sum(F.size("keys"))).first()[0], PORTION_ROWS)

    def held_apart(part: int) -> DataFrame:
        own = nodes.select("id", F.filter("keys", lambda k: F.pmod(k, F.lit(parts)) == part).alias("keys")) if parts > 1 else nodes
        rooted = own.join(roots, "id", "left").select("id", F.coalesce("root", "id").alias("root"), F.explode("keys").alias("key"))
        several = written(rooted.groupBy("key").agg(F.min("root").alias("x"), F.max("root").alias("y"), F.count("*").alias("n")).where("x != y").select("key", "n"))
        return spread_join(rooted, several, "key", several).select("key", "id", "root", "n")

    return written(*map(held_apart, range(parts)))


def bridge_pairs(met: DataFrame) -> DataFrame:
    """Pairs of each row of divided groups with two members of its group, chosen by a hash, that are of another class."""
    of = met.groupBy("key").agg(*[end(F.struct(F.xxhash64(F.lit("bridge"), "key", "id").alias("rank"), "id", "root")).alias(c) for end, c in ((F.min, "lo"), (F.max, "hi"))], F.max("n").alias("n"))
    ends = written(of.select("key", "n", F.array("lo", "hi").alias("ends")))
    both = spread_join(met.select("key", "id", "root"), ends.select("key", "ends"), "key", ends).select("id", "root", F.explode("ends").alias("e"))
    return ordered(both.where("e.root != root").select(F.col("id").alias("a"), F.col("e.id").alias("b")))


def rest_pairs(met: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """Distinct pairs (a, b) of nodes that share a group, that sketches allow, and that are of different classes.

    A large group is cut into blocks of about `BLOCK`, and every two blocks meet in a group of their
    own; sketches travel with the rows, so a pair that isn't similar is dropped within the join that
    compares it, and never becomes a row. A pair that shares several shingles counts at the first.
    """
    # a node's shared keys, at most those of its prefix: each row has those before its own
    by = written(met.groupBy("id", "root").agg(F.sort_array(F.collect_list(F.struct("key", "n"))).alias("keys")).join(nodes.select("id", "size", "sketch"), "id"))
    k = F.size("keys").cast("long")
    parts = portions(by.agg(F.sum(k * (k - 1) * 4 + k * (SKETCH * 8 + 32))).first()[0], PORTION_BYTES)
    own = ("id", "size", "sketch", "root", "earlier", "own")

    def compared(part: int) -> DataFrame:
        keyed = by.select("id", "size", "sketch", "root", "keys", F.posexplode("keys").alias("pos", "k")).where(F.pmod("k.key", F.lit(parts)) == part)
        cut = keyed.select("id", "size", "sketch", "root", F.col("k.key").alias("key"), F.slice("keys.key", 1, F.col("pos")).alias("earlier"), F.ceil(F.col("k.n") / BLOCK).cast("int").alias("blocks"))
        cut = cut.withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
        every = cut.select("key", *own, F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
        every = every.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), *own).repartition("key", "i", "j")  # once for both sides
        x, y = (every.select("key", "i", "j", *[F.col(c).alias(f"{c}_{side}") for c in own]) for side in "ab")
        apart = (F.col("id_a") < F.col("id_b")) & (F.col("root_a") != F.col("root_b")) & ((F.col("own_a") != F.col("own_b")) | (F.col("x.i") == F.col("x.j")))
        similar = may_be_similar(similarity, F.col("size_a"), F.col("sketch_a"), F.col("size_b"), F.col("sketch_b")) & ~F.arrays_overlap("earlier_a", "earlier_b")
        same = [F.col(f"x.{c}") == F.col(f"y.{c}") for c in ("key", "i", "j")]
        return x.alias("x").join(y.alias("y").hint("merge"), same[0] & same[1] & same[2] & apart & similar).select(F.col("id_a").alias("a"), F.col("id_b").alias("b")).distinct()

    return written(*map(compared, range(parts)))


def verified(pairs: DataFrame, texts: DataFrame, n: int, similarity: float) -> DataFrame:
    """The pairs whose whole shingle sets have the similarity (Jaccard); sets without shingles are equal."""

    def work(batch: pa.RecordBatch) -> dict:
        keep = []
        for s, t in zip(batch.column("s").to_pylist(), batch.column("t").to_pylist(), strict=True):
            x, y = set(shingles(s, n)), set(shingles(t, n))
            both = len(x & y)
            keep.append(both >= similarity * (len(x) + len(y) - both))
        return {"a": batch.column("a"), "b": batch.column("b"), "keep": keep}

    both = pairs.join(texts.select(F.col("id").alias("a"), F.col("text").alias("s")), "a").join(texts.select(F.col("id").alias("b"), F.col("text").alias("t")), "b")
    return map_rows(both.select("a", "b", "s", "t"), work, "a long, b long, keep boolean").where("keep").select("a", "b")


def _classed(named: DataFrame, n: int, radius: int, similarity: float) -> tuple[DataFrame, DataFrame]:
    """The sketched rows (row keys, doc_id, node), and (node, class, component_id, best) of every node.

    best: (no id, doc_id, row keys) of the class's least row.
    """
    if not 0 < similarity <= 1:
        raise ValueError("a similarity above 0 and up to 1 is needed")
    full = written(sketches(named, n, KEYS, similarity))
    least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", *KEYS)).alias("best")
    one = full.groupBy("node").agg(least, *[F.first(c).alias(c) for c in ("fp", "size", "sketch", "fine", "prefix")])
    nodes = written(one.withColumn("id", F.monotonically_increasing_id()))
    rows = written(full.select(*KEYS, "doc_id", "node"))
    removed(full)
    let_go(named.sparkSession)

    def similar(pairs: DataFrame) -> DataFrame:
        wanted = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
        # a table of known size: where it is small, texts needn't be shuffled to be found
        place = written(nodes.join(wanted, "id").select("id", *[F.col(f"best.{k}").alias(k) for k in KEYS]))
        texts = named.select(*KEYS, "text").join(place, KEYS).select("id", "text")
        links = written(verified(pairs, texts, n, similarity))
        let_go(named.sparkSession)
        return links

    pairs = written(allowed(ball_pairs(nodes, radius), nodes, similarity).union(star_pairs(nodes, similarity)).distinct())
    likely = similar(pairs)
    # what groups still hold apart: two members of each first, as most of their links follow from a few; then all pairs
    met = divided(nodes.select("id", F.col("prefix").alias("keys")), likely)
    let_go(named.sparkSession)
    bridges = written(allowed(bridge_pairs(met.where(F.col("n") > BRIDGED)).join(pairs, ["a", "b"], "left_anti"), nodes, similarity))
    links = written(likely.union(similar(bridges)))
    rest = rest_pairs(divided(met.groupBy("id").agg(F.collect_list("key").alias("keys")), links), nodes, similarity).join(pairs.union(bridges), ["a", "b"], "left_anti")
    links = links.union(similar(written(allowed(rest, nodes, similarity))))
    rooted = nodes.select("id", "node", "best").join(components(links).withColumnRenamed("node", "id"), "id", "left").withColumn("class", F.coalesce("root", "id"))
    best = rooted.groupBy("class").agg(F.min("best").alias("first"))
    return rows, written(spread_join(rooted.select("node", "class"), best, "class").select("node", "class", F.col("first.doc_id").alias("component_id"), F.col("first").alias("best")))


def near_duplicates(named: DataFrame, n: int = 5, radius: int = 2, similarity: float = 0.8) -> DataFrame:
    """Row keys, doc_id, node, class, component_id and keep of every row of docs with row keys.

    keep marks one row of each class: the least doc_id, then the first by row keys.
    """
    rows, nodes = _classed(named, n, radius, similarity)
    marked = spread_join(rows.select(*KEYS, "doc_id", "node"), nodes, "node")
    return marked.withColumn("keep", F.struct(*KEYS) == F.struct(*[F.col(f"best.{k}").alias(k) for k in KEYS])).drop("best")


def without_near_duplicates(docs: DataFrame, n: int = 5, radius: int = 2, similarity: float = 0.8) -> DataFrame:
    """Docs, with all their columns, one of each class of near-duplicates.

    Candidates are of two sources: meetings of fingerprints in the ball, which at 64 bits and radius
    2 find few of the wanted pairs, and an exact prefix join of shingle sets, which finds all.
    """
    named = row_keys(docs)
    rows, nodes = _classed(named, n, radius, similarity)
    kept = nodes.select(*[F.col(f"best.{k}").alias(k) for k in KEYS]).distinct()
    dropped = written(rows.select(*KEYS).join(kept, KEYS, "left_anti"))
    return named.join(dropped, KEYS, "left_anti").drop(*KEYS)
