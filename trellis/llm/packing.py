"""Best-fit packing by exact-complement hashing.

Documents become tokens plus an end token; only documents longer than a sequence are cut, into
whole sequences after a first piece that may be shorter. Lengths are at most `size`, so the whole
table is a histogram of `size` counts, and what is packed with what depends on it alone:

1. lengths are looked up, longest first, in indexes of single, pair and triple length sums; a
   combination that exactly fills the gap is consumed as often as all its members last;
2. what remains is placed best-fit, in order of falling length, by groups of equal bins.

The driver sees `size` counts and makes at most a few templates for each length. Each piece then
finds its sequence from its rank among the pieces of its length, which is summed from counts by
task, so a length that a third of all rows have is never gathered in one task.

Nulls: a null text is an empty document (the end token alone). Repeated rows are packed each on
their own. Pieces of equal length (ties) are told apart by the order of their tasks alone, so
sequence numbers may differ between runs, but not how many there are. Texts have any length; an
empty table gives no pieces.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checkpointed, rank_in_key, row_batches

END = 2


#: Added tokens of a vocabulary: (their text, their id).
Added = tuple[tuple[str, int], ...]


@lru_cache(maxsize=2)
def encoder(ranks_path: str, pattern: str, added: Added = ()) -> Callable[[str], list[int]]:
    """Text to ids by the byte-level BPE as ranks; same ids as its JSON form, several times faster (tested).

    `added` are the JSON form's own tokens, whose text gives their id wherever it stands.
    """
    import tiktoken

    with open(ranks_path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    code, names = tiktoken.Encoding("bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens=dict(added)), [a for a, _ in added]
    return lambda text: code.encode(text, allowed_special=set(names), disallowed_special=()) if any(a in text for a in names) else code.encode_ordinary(text)


def cut(n: int, size: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens."""
    first = n % size or size
    return [(0, min(n, first))] + [(at, size) for at in range(first, n, size)] if n else []


# --- plan ---------------------------------------------------------------------------------------


@dataclass
class Template:
    lengths: list[int]
    copies: int


@dataclass
class Complements:
    """Availability of lengths, with look-up of one, two or three of them by their sum."""

    counts: np.ndarray
    have: np.ndarray = field(init=False)

    def __post_init__(self):
        self.have = self.counts > 0

    def enough(self, parts: tuple[int, ...]) -> int:
        """How often all parts can be taken together."""
        return min((int(self.counts[p]) // parts.count(p) for p in parts), default=0)

    def take(self, parts: tuple[int, ...], n: int) -> None:
        for p in parts:
            self.counts[p] -= n
            self.have[p] = self.counts[p] > 0

    def pairs(self, total: int) -> Iterator[tuple[int, int]]:
        """Pairs of available lengths of this sum, the widest apart first."""
        if total < 2:
            return
        b = np.arange(1, total // 2 + 1)
        for x in b[self.have[b] & self.have[total - b]]:
            yield int(total - x), int(x)

    def triples(self, total: int) -> Iterator[tuple[int, int, int]]:
        """Triples of available lengths of this sum, with the largest falling."""
        for a in range(total - 2, (total - 1) // 3, -1):
            if self.have[a]:
                for b, c in self.pairs(total - a):
                    if b <= a:
                        yield a, b, c


def plan(histogram: dict[int, int], size: int) -> list[Template]:
    """Templates (lengths of one sequence, number of such sequences) that hold every piece once."""
    counts = np.zeros(size + 1, np.int64)
    for n, k in histogram.items():
        counts[n] = k
    left, out = Complements(counts), []

    def consume(parts: tuple[int, ...]) -> None:
        if (n := left.enough(parts)) > 0:
            left.take(parts, n)
            out.append(Template(list(parts), n))

    consume((size,))
    for a in range(size - 1, size // 2 - 1, -1):
        if left.have[a]:
            consume((a, size - a))
    for arity in (left.pairs, left.triples):
        for a in range(size - 1, 0, -1):
            tried = arity(size - a) if left.have[a] else ()
            for rest in tried:
                consume((a, *rest))
                if not left.have[a]:
                    break
    bins: dict[int, list[Template]] = {}  # by free space
    for a in range(size, 0, -1):
        todo = int(left.counts[a])
        for space in range(a, size):
            while todo and bins.get(space):
                group = bins[space].pop()
                each = min(space // a, -(-todo // group.copies))
                n = min(group.copies, todo // each)
                bins.setdefault(space - each * a, []).append(Template(group.lengths + [a] * each, n))
                todo -= n * each
                if n < group.copies:
                    bins[space].append(Template(group.lengths, group.copies - n))
        per = size // a
        for each, n in ((per, todo // per), (todo % per, 1)):
            if each and n:
                bins.setdefault(size - each * a, []).append(Template([a] * each, n))
    return out + [t for group in bins.values() for t in group if t.copies]


def places(templates: list[Template]) -> dict[int, list[tuple[int, int, int, int]]]:
    """By length: (first rank, past-the-last rank, first sequence, offset) of every slot."""
    out: dict[int, list[tuple[int, int, int, int]]] = {}
    used: dict[int, int] = {}
    base = 0
    for t in templates:
        offset = 0
        for n in t.lengths:
            at = used.get(n, 0)
            out.setdefault(n, []).append((at, at + t.copies, base, offset))
            used[n] = at + t.copies
            offset += n
        base += t.copies
    return out


# --- Spark --------------------------------------------------------------------------------------

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, __part int, __local long"


def pieces(docs: DataFrame, ranks_path: str, pattern: str, added: Added = (), size: int = 1024) -> DataFrame:
    """A row for each piece, with its rank among its task's pieces of its length."""
    types = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("__part", pa.int32()), ("__local", pa.int64())])

    def run(batches):
        seen, part = np.zeros(size + 1, np.int64), TaskContext.get().partitionId()
        code = encoder(ranks_path, pattern, added)
        for batch in row_batches(batches):
            rows = []
            for key, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                ids = np.array([*code(text or ""), END], "<u4")
                for k, (at, n) in enumerate(cut(len(ids), size)):
                    rows.append((key, k, at, n, zlib.crc32(ids[at : at + n].tobytes()), part, int(seen[n])))
                    seen[n] += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows, strict=True), types, strict=True)] if rows else [pa.array([], t.type) for t in types], schema=types)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECES)


def pack(spark: SparkSession, docs: DataFrame, ranks_path: str, pattern: str, added: Added = (), size: int = 1024) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    rows = checkpointed(pieces(docs, ranks_path, pattern, added, size))
    counts = {r["length"]: r["n"] for r in rows.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `size` rows
    lookup = spark.createDataFrame(list(places(plan(counts, size)).items()), "length long, __slots array<struct<lo: bigint, hi: bigint, base: bigint, offset: bigint>>")
    ranked = rank_in_key(rows, "length", "__part", "__local", "__rank").join(F.broadcast(lookup), "length")
    slot = F.filter("__slots", lambda s: (s["lo"] <= F.col("__rank")) & (F.col("__rank") < s["hi"]))[0]
    return ranked.withColumn("__s", slot).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("__s.base") + F.col("__rank") - F.col("__s.lo")).alias("sequence_id"), F.col("__s.offset").alias("offset"))
