"""Benchmark decontamination with an Aho-Corasick automaton over normalised test items.

Texts are normalised to words (A-Z lower-cased; a word is a run of ASCII letters and digits and
of anything beyond ASCII). Every 13 consecutive words of an item are a pattern; an item of fewer
words is one pattern. A document is scanned once, all overlapping occurrences are found, and
their offsets are mapped back to words and from there to the original text.

A benchmark has any size. `MOST_BYTES` of items are sent out at a time, and an automaton holds
`MOST_STATES` characters of windows; a task that needs several builds one after the other and
scans a batch of documents with each. Hits of all of them are merged, so results don't depend on
how the benchmark is cut. A benchmark beyond `MOST_BYTES` is worked off part by part, and only
hits of the parts are shuffled, by the row's key.

Nulls: a null text has no words and is clean; an item with a null id or text is left out. Items
of the same id count once, repeated rows are judged alike. An empty benchmark hits nothing.
Texts and items have any length.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import accumulate, chain, islice

import ahocorasick
import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import KEYS, ready, row_keys, written

#: Words of one window.
WINDOW = 13
#: Characters of windows in one automaton, which takes some 50 bytes for each.
MOST_STATES = 4 << 20
#: Item bytes that are sent to the executors at a time.
MOST_BYTES = 32 << 20
#: Bytes to what they normalise to: separators (0-2F, 3A-60 but A-Z, 7B-7F) to a space, A-Z to a-z.
_FOLD = bytes(32 if b < 0x30 or 0x3A <= b < 0x41 or 0x5B <= b <= 0x60 or 0x7B <= b <= 0x7F else b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))
_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


def normal_words(text: str | None) -> list[str]:
    # only blanks split here: str.split() would also split at separators beyond ASCII, which belong to words
    return [x.decode("utf-8", "surrogatepass") for x in text.encode("utf-8", "surrogatepass").translate(_FOLD).split(b" ") if x] if text else []


def windows(items: Iterable[tuple[str, str]], window: int = WINDOW) -> Iterator[tuple[str, int, str]]:
    """(text of the window with a blank at both ends, its number of words, item id) of every window."""
    for key, text in items:
        w = normal_words(text)
        for at in range(max(1, len(w) - window + 1) if w else 0):
            part = w[at : at + window]
            yield f" {' '.join(part)} ", len(part), key


def automata(items: Iterable[tuple[str, str]], window: int = WINDOW, most: int = MOST_STATES) -> Iterator[ahocorasick.Automaton]:
    """Automata of at most `most` characters of windows each, made as they are asked for."""
    held: dict[str, tuple[int, set[str]]] = {}
    size = 0

    def made() -> ahocorasick.Automaton:
        auto = ahocorasick.Automaton()
        for text, (n, keys) in held.items():
            auto.add_word(text, (len(text), n, tuple(sorted(keys))))
        auto.make_automaton()
        return auto

    for text, n, key in windows(items, window):
        if text not in held:
            if held and size + len(text) > most:
                yield made()
                held, size = {}, 0
            size += len(text)
        held.setdefault(text, (n, set()))[1].add(key)
    if held:
        yield made()


class Scanner:
    """Finds all windows of items in texts; a single automaton is kept, several are made anew for each batch."""

    def __init__(self, items: tuple[tuple[str, str], ...], window: int = WINDOW, most: int = MOST_STATES):
        self.make = lambda: automata(items, window, most)
        few = sum(len(text) for text, *_ in islice(windows(items, window), most)) <= most
        self.kept = list(self.make()) if few else None

    def __call__(self, texts: list[str | None]) -> list[tuple[int, list[tuple[int, int, tuple[str, ...]]]]]:
        """For each text its number of words, and (first word, past-the-last word, item ids) of every occurrence."""
        lists = [normal_words(t) for t in texts]
        found: list[list[tuple[int, int, tuple[str, ...]]]] = [[] for _ in lists]
        starts: dict[int, np.ndarray] = {}  # where each word begins in the flat text
        for auto in self.kept if self.kept is not None else self.make():
            for k, w in enumerate(lists):
                for end, (size, n, keys) in auto.iter(f" {' '.join(w)} ") if w else ():
                    if k not in starts:
                        starts[k] = np.fromiter(accumulate((len(x) + 1 for x in w), initial=1), np.int64, len(w) + 1)
                    first = int(np.searchsorted(starts[k], end - size + 2))
                    found[k].append((first, first + n, keys))
        return [(len(w), f) for w, f in zip(lists, found, strict=True)]


@lru_cache(maxsize=2)
def _scanner(items: tuple[tuple[str, str], ...], window: int, most: int) -> Scanner:
    return Scanner(items, window, most)


def united(spans: Iterable[tuple[int, int]]) -> list[list[int]]:
    """Spans that meet or overlap as one."""
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


def original_spans(text: str, hits: Iterable[tuple[int, int]]) -> list[list[int]]:
    """Character spans of the original text that runs of words cover, merged."""
    raw = text.encode("utf-8", "surrogatepass")
    at = [m.span() for m in _WORD.finditer(raw)]
    where = lambda b: len(raw[:b].decode("utf-8", "surrogatepass"))
    return [[where(a), where(b)] for a, b in united((at[a][0], at[b - 1][1]) for a, b in hits)]


#: What a part of the benchmark says of a text: runs of hit words, ids of items, character offsets in the original.
FOUND = "n_words long, hits array<struct<a: int, b: int>>, items array<string>, spans array<struct<a: int, b: int>>"


def found_column(items: tuple[tuple[str, str], ...], window: int = WINDOW, most: int = MOST_STATES, text: str = "text") -> Column:
    """What the items hit in a text, as a struct column: only texts travel to Python."""

    @F.pandas_udf(FOUND)
    def judge(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        scan = _scanner(items, window, most)
        pair = lambda spans: [{"a": a, "b": b} for a, b in spans]
        for part in parts:
            rows = []
            for t, (n, found) in zip(part, scan(list(part)), strict=True):
                runs = united((a, b) for a, b, _ in found)
                rows.append((n, pair(runs), sorted({k for f in found for k in f[2]}), pair(original_spans(t, runs)) if runs else []))
            yield pd.DataFrame(rows, columns=["n_words", "hits", "items", "spans"])

    return judge(F.col(text))


def benchmark_parts(benchmark: DataFrame, most_bytes: int = MOST_BYTES) -> Iterator[tuple[tuple[str, str], ...]]:
    """The items in parts of about `most_bytes`, brought to the driver one part after the other; one empty part at least."""
    usable = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("string").alias("key"), "text").distinct()
    size = usable.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    count = max(1, -(-size // most_bytes))
    for k in range(count):
        rows = usable if count == 1 else usable.where(F.pmod(F.xxhash64("key", "text"), F.lit(count)) == k)
        yield tuple(sorted((r["key"], r["text"]) for r in rows.collect()))


def _merged(spans: Column) -> Column:
    """Spans of several parts, those that meet or overlap as one."""
    kind = "array<struct<a: int, b: int>>"

    def add(done: Column, x: Column) -> Column:
        last = F.element_at(done, -1)
        wider = F.concat(F.slice(done, 1, F.size(done) - 1), F.array(F.struct(last["a"].alias("a"), F.greatest(last["b"], x["b"]).alias("b"))))
        return F.when((F.size(done) > 0) & (x["a"] <= F.try_element_at(done, F.lit(-1))["b"]), wider).otherwise(F.concat(done, F.array(x)))

    return F.aggregate(F.array_sort(spans), F.array().cast(kind), add)


def with_found(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, most_bytes: int = MOST_BYTES, most_states: int = MOST_STATES) -> DataFrame:
    """Docs with `__found` (FOUND) of the whole benchmark."""
    ready(docs.sparkSession)
    parts = benchmark_parts(benchmark, most_bytes)
    first = next(parts)
    second = next(parts, None)
    if second is None:
        return docs.withColumn("__found", found_column(first, window, most_states))
    named = row_keys(docs)
    hits = None
    for part in chain((first, second), parts):
        own = written(named.select(*KEYS, found_column(part, window, most_states).alias("f")).where("size(f.hits) > 0"))
        hits = own if hits is None else hits.union(own)
    by = hits.groupBy(*KEYS).agg(*[F.flatten(F.collect_list(f"f.{c}")).alias(c) for c in ("hits", "items", "spans")])
    merged = by.select(*KEYS, _merged(F.col("hits")).alias("hits"), F.array_sort(F.array_distinct("items")).alias("items"), _merged(F.col("spans")).alias("spans"))
    words = named.withColumn("__words", found_column((), window, most_states)["n_words"])
    none = {"hits": "array<struct<a: int, b: int>>", "items": "array<string>", "spans": "array<struct<a: int, b: int>>"}
    out = words.join(merged.withColumnsRenamed({c: f"__{c}" for c in none}), KEYS, "left")
    return out.withColumn("__found", F.struct(F.col("__words").alias("n_words"), *[F.coalesce(f"__{c}", F.array().cast(kind)).alias(c) for c, kind in none.items()])).drop("__words", *[f"__{c}" for c in none], *KEYS)


def n_hit(found: str = "__found") -> Column:
    return F.aggregate(F.col(f"{found}.hits"), F.lit(0).cast("long"), lambda n, x: n + x["b"] - x["a"])


def contaminated(share: int) -> Column:
    """Whether one word in `share`, or more, is hit."""
    return (n_hit() > 0) & (share * n_hit() >= F.col("__found.n_words"))


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20, **bounds: int) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated and spans for every document.

    contaminated: one word in `share`, or more, is hit. spans: offsets in the original text.
    """
    out = with_found(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), benchmark, window, **bounds)
    digest = F.sha2(F.array_join("__found.items", ","), 256)
    return out.select("doc_id", "__found.n_words", n_hit().alias("n_hit"), F.size("__found.items").cast("long").alias("n_items"), digest.alias("items_sha256"), contaminated(share).alias("contaminated"), "__found.spans")


def without_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20, **bounds: int) -> DataFrame:
    """Docs, with all their columns, that aren't contaminated."""
    return with_found(docs, benchmark, window, **bounds).where(~contaminated(share)).drop("__found")
