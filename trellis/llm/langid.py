"""Language identification of mixed text: Viterbi over words, with a penalty for switching.

A word's scripts narrow the languages that may claim it (those seen with that script in
training). Of these, each gives the word a score: the smoothed log likelihood of its character
n-grams of one to four letters. Viterbi decoding over a document's words, with a penalty for
each change of language, labels spans; the document takes the language with the most letters.

Learns from documents with a language outside the held-out fold: a bounded sample (about
`PER_LANGUAGE` documents of each, by a hash of the id). More than `MOST_LANGUAGES` of them are an error.

Nulls: null text, or text without a letter, is `und` with score 0. Without training rows
everything is `und`. Repeated rows get equal results; of languages with equally many letters, or
equal scores, the first by name counts. Texts of any length are read whole.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, hash_share, row_batches

PER_LANGUAGE = 3000
MOST_LANGUAGES = 256
BUCKETS = 1 << 16
#: Log probability lost by a change of language from a word to the next.
SWITCH = 6.0
#: n-grams of a word overlap, so their sum says too much by about this factor.
OVERLAP = 2.5
_WORD = re.compile(r"[^\W\d_]+")

# First and last code points of scripts' main blocks.
SCRIPTS = {
    "latin": [(0x41, 0x24F), (0x1E00, 0x1EFF)], "greek": [(0x370, 0x3FF)], "cyrillic": [(0x400, 0x52F)], "armenian": [(0x530, 0x58F)],
    "hebrew": [(0x590, 0x5FF)], "arabic": [(0x600, 0x6FF), (0x750, 0x77F)], "devanagari": [(0x900, 0x97F)], "bengali": [(0x980, 0x9FF)],
    "tamil": [(0xB80, 0xBFF)], "thai": [(0xE00, 0xE7F)], "georgian": [(0x10A0, 0x10FF)], "hangul": [(0x1100, 0x11FF), (0xAC00, 0xD7AF)],
    "kana": [(0x3040, 0x30FF)], "han": [(0x3400, 0x9FFF)],
}
NAMES = [*SCRIPTS, "other"]


def code_points(words: list[str]) -> np.ndarray:
    """The words between blanks, one array of code points."""
    return np.frombuffer(f" {' '.join(words)} ".encode("utf-32-le", "surrogatepass"), "<u4")


def scripts(words: list[str]) -> np.ndarray:
    """Number of the script of each word's first letter."""
    c = code_points(words)
    first = c[1:][c[:-1] == 32][: len(words)]
    out = np.full(len(words), len(SCRIPTS))
    for k, ranges in enumerate(SCRIPTS.values()):
        for lo, hi in ranges:
            out[(first >= lo) & (first <= hi)] = k
    return out


def grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(word number, bucket) of all 1- to 4-grams of the words, each between blanks."""
    c = code_points(words).astype(np.uint64)
    blank = c == 32
    number = np.cumsum(blank) - 1  # a blank counts to the word after it
    owners, buckets = [], []
    with np.errstate(over="ignore"):
        for n in (1, 2, 3, 4):
            m = len(c) - n + 1
            if m <= 0:
                continue
            inner = np.zeros(m, bool)  # whether a blank lies between the ends
            for k in range(1, n - 1):
                inner |= blank[k : k + m]
            h = np.full(m, n, np.uint64)
            for k in range(n):
                h = h * np.uint64(1000003) + c[k : k + m]
            use = ~inner & ~(blank[:m] if n == 1 else blank[:m] & blank[n - 1 : n - 1 + m])
            owners.append(number[:m][use])
            buckets.append(((h[use] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(48)).astype(np.int64) % BUCKETS)
    return np.concatenate(owners), np.concatenate(buckets)


def words(text: str | None) -> list[str]:
    return _WORD.findall(text.lower()) if text else []


@dataclass(frozen=True)
class Model:
    languages: tuple[str, ...]
    scores: np.ndarray  # BUCKETS x languages, log likelihoods less their mean over languages
    scripts: np.ndarray  # scripts x languages, True where seen


def counts_of(ws: list[str]) -> np.ndarray:
    """How often the words hold each n-gram bucket, then how many are of each script."""
    return np.concatenate([np.bincount(grams(ws)[1], minlength=BUCKETS), np.bincount(scripts(ws), minlength=len(NAMES))])


def build(counts: dict[str, np.ndarray], scripts: dict[str, np.ndarray]) -> Model:
    names = tuple(sorted(counts))
    c = np.array([counts[n] for n in names], float).T.reshape(BUCKETS, len(names))
    p = np.log((c + 0.1) / (c.sum(0) + 0.1 * BUCKETS)) if len(names) else c
    seen = np.array([scripts[n] for n in names], float).T.reshape(len(NAMES), len(names))
    return Model(names, p - p.mean(1, keepdims=True) if len(names) else p, seen > 0.001 * np.maximum(seen.sum(0), 1) if len(names) else seen > 0)


class Labeller:
    """Scores of words are remembered, up to a bound."""

    def __init__(self, model: Model, switch: float = SWITCH, most: int = 200_000):
        self.model, self.switch, self.most = model, switch, most
        self.row: dict[str, int] = {}  # of a word in `table`
        self.table = np.zeros((0, len(model.languages)))
        self.columns = np.ascontiguousarray(model.scores.T)

    def look_up(self, need: set[str]) -> None:
        if len(self.row) + len(need) > self.most:
            self.row, self.table = {}, self.table[:0]
        if not (new := [w for w in need if w not in self.row]):
            return
        owner, bucket = grams(new)
        sums = np.stack([np.bincount(owner, weights=column[bucket], minlength=len(new)) for column in self.columns], axis=1) / OVERLAP
        allowed = self.model.scripts[scripts(new)]
        sums = np.where(allowed | ~allowed.any(1, keepdims=True), sums, sums - 50.0)
        self.row.update(zip(new, range(len(self.table), len(self.table) + len(new)), strict=True))
        self.table = np.concatenate([self.table, sums])

    def label(self, lists: list[list[str]]) -> list[np.ndarray]:
        """Language numbers of the words of each document: Viterbi over all documents side by side."""
        self.look_up(set(chain.from_iterable(lists)))
        order = sorted(range(len(lists)), key=lambda k: -len(lists[k]))
        size = np.array([len(lists[k]) for k in order])
        n, k = len(lists), len(self.model.languages)
        flat = self.table[np.fromiter((self.row[w] for d in order for w in lists[d]), np.int64, int(size.sum()))].reshape(-1, k)
        start = np.concatenate([[0], np.cumsum(size)[:-1]])
        steps, value = int(size.max(initial=0)), np.zeros((n, k))
        stay = np.ones((len(flat), k), bool)  # whether the best way to a word's language is from the same one
        best = np.zeros(len(flat), np.int16)  # the best language of the word before
        alive = np.searchsorted(-size, -np.arange(steps), side="left")  # documents with more than t words
        for t in range(steps):
            m = int(alive[t])
            at = start[:m] + t
            if t:
                v = value[:m]
                top = v.argmax(1)
                jump = v[np.arange(m), top] - self.switch
                keep = v >= jump[:, None]
                stay[at], best[at] = keep, top
                value[:m] = np.where(keep, v, jump[:, None]) + flat[at]
            else:
                value[:m] = flat[at]
        out = [np.zeros(0, np.int64)] * n
        now, path = value.argmax(1), np.zeros(len(flat), np.int64)
        for t in range(steps - 1, -1, -1):
            m = int(alive[t])
            at = start[:m] + t
            path[at] = now[:m]
            if t:
                now[:m] = np.where(stay[at, now[:m]], now[:m], best[at])
        for r, d in enumerate(order):
            out[d] = path[start[r] : start[r] + size[r]]
        return out

    def documents(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        """Language and share of letters it holds, for each text."""
        lists = [words(t) if self.model.languages else [] for t in texts]
        names, shares = [], []
        for ws, path in zip(lists, self.label(lists) if any(lists) else [[]] * len(lists), strict=True):
            if not ws:
                names.append("und")
                shares.append(0.0)
                continue
            letters = np.bincount(path, weights=[len(w) for w in ws], minlength=len(self.model.languages))
            names.append(self.model.languages[int(letters.argmax())])
            shares.append(float(letters.max() / letters.sum()))
        return names, shares

    def spans(self, text: str | None) -> list[tuple[int, int, str]]:
        """(start, end, language) of the runs of one language in a text."""
        found = list(_WORD.finditer(text or ""))
        out: list[tuple[int, int, str]] = []
        for m, k in zip(found, self.label([[m[0].lower() for m in found]])[0], strict=True):
            name = self.model.languages[int(k)]
            out[-1:] = [(out[-1][0], m.end(), name)] if out and out[-1][2] == name else [*out[-1:], (m.start(), m.end(), name)]
        return out


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Model:
    usable = docs.where((fold("doc_id", 3) != 1) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = {r["lang"]: r["n"] for r in usable.groupBy("lang").agg(F.count("*").alias("n")).limit(MOST_LANGUAGES + 1).collect()}
    if len(counts) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages: none is left out silently")
    counts = dict(sorted(counts.items(), key=lambda x: (-x[1], x[0])))
    sample = usable.where(hash_share(per_language, counts, "lang", "doc_id")).select("lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, np.ndarray] = {}
        for part in row_batches(batches):
            by: dict[str, list[str]] = {}
            for lang, text in zip(part.column("lang").to_pylist(), part.column("text").to_pylist(), strict=True):
                by.setdefault(lang, []).extend(words(text))
            for lang, ws in by.items():
                if ws:
                    seen[lang] = seen.get(lang, 0) + counts_of(ws)
        for lang, total in seen.items():
            k = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(k)), pa.array(k, pa.int32()), pa.array(total[k], pa.int64())], names=["lang", "k", "n"])

    counted, written = {n: np.zeros(BUCKETS) for n in counts}, {n: np.zeros(len(NAMES)) for n in counts}
    # a row for each language and bucket at most
    for r in sample.mapInArrow(run, "lang string, k int, n long").groupBy("lang", "k").agg(F.sum("n").alias("n")).toLocalIterator():
        (counted if r["k"] < BUCKETS else written)[r["lang"]][r["k"] % BUCKETS] = r["n"]
    return build(counted, written)


def identify(docs: DataFrame, per_language: int = PER_LANGUAGE) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row."""
    model = train(docs, per_language)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labeller = Labeller(model)
        for part in row_batches(batches, 1024):
            names, shares = labeller.documents(part.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(names), pa.array(shares)], names=["doc_id", "held_out", "lang_pred", "score"])

    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold("doc_id", 3) == 1).alias("held_out"), "text")
    return given.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")
