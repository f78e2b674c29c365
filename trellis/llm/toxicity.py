"""Toxicity behind a noisy channel: restore obfuscated words, then score the restored text.

A suspicious span (digits or symbols inside a word, single letters with separators between them,
a letter three times in a row) is an observation of a hidden word. Its characters make a lattice:
each may stand for itself, for the letters it is used for, or, as a separator or a repetition,
for none. Spans have any length. Viterbi decoding under a character trigram model picks the reading; the model counts
the characters of all documents, and of the words that labels show to matter.

Restored words carry weights: smoothed log odds, learned from labelled documents, of the word
and of its beginnings (so that inflected forms count). A document is judged by its strongest
words; a logistic calibration on other labelled rows makes that a probability.

Labels come from a bounded sample (`PER_CLASS` documents of each class by a hash of the id).
Character counts cover the whole corpus: they are summed in each task and again by trigram.

Nulls: a null text is an empty one. With labels of one class, or none, every score is the
smoothed share of label 1. Repeated rows get equal scores. Of two readings of equal probability
the one found first counts, of two features of equal weight either. Texts, words and spans have
any length: each is read in time in proportion to it.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ROWS_AT_ONCE, fold, labelled_sample, logistic, map_rows, prior_weights, row_batches, sigmoid

#: Labelled documents taken of each class.
PER_CLASS = 3000
#: Standard deviations that a feature's count in toxic documents must be above its expectation.
LEAST_Z = 4.0
#: Toxic documents that a feature must be seen in.
LEAST_SEEN = 4
#: Letters of the model: a-z, anything else that is a letter, and the edge of a word.
OTHER, EDGE, SIZE = 26, 27, 28

# What symbols and digits stand for.
LEET = {"0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "il", "|": "il", "+": "t", "€": "e", "£": "l", "*": "aeiou", "#": "h"}
# Letters of other scripts that look like Latin ones.
LOOKALIKE = {"а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "і": "i", "ѕ": "s", "ј": "j", "ο": "o", "α": "a", "ε": "e", "ι": "i", "ν": "v", "τ": "t", "κ": "k"}
_SIGN = "0-9@$!|+€£*#"
_LETTER = r"[^\W\d_]"
_HIDDEN = re.compile("[­​-‏⁠﻿]")
_SPACED = rf"(?<!\S)(?:{_LETTER}|[{_SIGN}])(?P<gap>[ .\-_*~·/]{{1,2}})(?:{_LETTER}|[{_SIGN}])(?:(?P=gap)(?:{_LETTER}|[{_SIGN}])){{2,}}(?![^\s.,;:?!])"
# possessive, and begun at the start of a word only: each takes time in proportion to the word
_LEET = rf"(?<![^\s(\"'])(?:{_LETTER}++[{_SIGN}]++|[{_SIGN}]{{1,3}}{_LETTER})(?:{_LETTER}|[{_SIGN}])*+(?![^\s.,;:?)\"'])"
_REPEAT = rf"(?<!{_LETTER}){_LETTER}*?(?P<x>{_LETTER})(?P=x)(?P=x){_LETTER}*+"
_SPLIT = rf"(?<![\w.@])(?:{_LETTER}{{1,3}}[.\-_~·]){{2,}}{_LETTER}{{1,4}}(?![\w@])"
SUSPECT = re.compile(f"{_SPACED}|{_LEET}|{_SPLIT}|{_REPEAT}")
_QUICK = re.compile(rf"[{_SIGN}]|({_LETTER})\1\1|(?<!\w)\w[ .\-_*~·/]{{1,2}}\w[ .\-_*~·/]{{1,2}}\w(?!\w)|\w[.\-_~·]\w")
WORD = re.compile(rf"{_LETTER}+")
#: Characters of a span whose reading is remembered; longer ones are decoded each time.
REMEMBERED = 64


def folded(text: str) -> str:
    """Lower case, compatibility forms composed, invisible characters dropped, look-alikes in mixed words replaced."""
    if not text.isascii():
        text = _HIDDEN.sub("", unicodedata.normalize("NFKC", text))
        if any(c in text for c in LOOKALIKE):
            text = WORD.sub(lambda m: "".join(LOOKALIKE.get(c, c) for c in m[0]) if any("a" <= c.lower() <= "z" for c in m[0]) else m[0], text.lower())
    return text.lower()


# --- character model ------------------------------------------------------------------------------


def trigrams(text: str) -> np.ndarray:
    """Counts of (two letters, letter) over the words of a text, edges included; SIZE**3 numbers."""
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    code = np.where((code >= 97) & (code <= 122), code - 97, np.where((code < 128) | (code == 160), EDGE, OTHER)).astype(np.int64)
    code = np.concatenate([[EDGE, EDGE], code, [EDGE]])
    key = (code[:-2] * SIZE + code[1:-1]) * SIZE + code[2:]
    return np.bincount(key, minlength=SIZE**3)


def corpus_trigrams(docs: DataFrame) -> np.ndarray:
    """Trigram counts of all documents: summed in each task, then by trigram (SIZE**3 at most)."""
    types = pa.schema([("k", pa.int32()), ("n", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(SIZE**3, np.int64)
        for part in row_batches(batches):
            total += trigrams(" ".join(t.lower() for t in part.column(0).to_pylist() if t))
        k = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(total[k], pa.int64())], schema=types)

    out = np.zeros(SIZE**3)
    for r in docs.select("text").mapInArrow(run, "k int, n long").groupBy("k").agg(F.sum("n").alias("n")).collect():
        out[r["k"]] = r["n"]
    return out


@dataclass(frozen=True)
class Model:
    log_p: np.ndarray  # of a letter after two, SIZE**3
    weights: dict[str, float]
    calibration: tuple[float, ...]


def language_model(counts: np.ndarray, known: dict[str, float]) -> np.ndarray:
    """Interpolated log probabilities; known words (and their strengths) count as much as all of the corpus."""
    extra = np.zeros(SIZE**3)
    for word, strength in known.items():
        extra += strength * trigrams(word)
    total = counts / max(1.0, counts.sum()) + (extra / extra.sum() if extra.sum() else 0)
    tri = total.reshape(SIZE, SIZE, SIZE)
    bi, uni = tri.sum(0), tri.sum((0, 1))
    p_uni = (uni + 1e-9) / (uni + 1e-9).sum()
    p_bi = bi / np.maximum(bi.sum(1, keepdims=True), 1e-300)
    p_tri = tri / np.maximum(tri.sum(2, keepdims=True), 1e-300)
    return np.log(0.8 * p_tri + 0.15 * p_bi[None] + 0.05 * p_uni[None, None]).ravel()


# --- decoding ---------------------------------------------------------------------------------------

#: Log probabilities of the channel: a sign put in, a letter said again (a third time is free), a
#: sign standing in, a letter kept, and a separator that is a real one.
DROP, REPEATED, STAND_IN, KEPT, PARTED = -4.0, -2.5, -0.3, -0.05, -5.0


def lattice(span: str) -> Iterator[list[tuple[str, float]]]:
    """For each observed character, what it may stand for ('' for nothing) and the channel's log probability."""
    before, earlier = "", ""
    for c in span:
        if c.isalpha():
            arcs = [(c, KEPT)]
            if c == before:
                arcs.append(("", KEPT if c == earlier else REPEATED))
        elif c in LEET:
            arcs = [(x, STAND_IN - math.log(len(LEET[c]))) for x in LEET[c]] + [("", DROP)]
        else:
            arcs = [("", KEPT), (" ", PARTED)]
        yield arcs
        before, earlier = c, before


#: Observed characters after which what all readings agree on is written down.
SETTLE = 2048


def traced(steps: list[dict], state: tuple[int, int]) -> tuple[list[str], list[tuple[int, int]]]:
    """What a state's best way says at each step, last first, and the states before each."""
    said, through = [], []
    for back in reversed(steps):
        state, c = back[state]
        said.append(c)
        through.append(state)
    return said, through


def decode(span: str, log_p: np.ndarray) -> str:
    """The most probable words behind a span of any length: Viterbi over the lattice, with the last two letters as state.

    Ways that survive soon have one past in common; it is written down and forgotten, so memory
    doesn't grow with the span.
    """
    number = lambda c: ord(c) - 97 if "a" <= c <= "z" else EDGE if c == " " else OTHER
    states: dict[tuple[int, int], float] = {(EDGE, EDGE): 0.0}
    steps: list[dict[tuple[int, int], tuple[tuple[int, int], str]]] = []  # where each state came from, and what it says
    settled: list[str] = []
    due = SETTLE
    for arcs in lattice(span):
        after: dict[tuple[int, int], float] = {}
        back: dict[tuple[int, int], tuple[tuple[int, int], str]] = {}
        for (a, b), score in states.items():
            for c, channel in arcs:
                if c:
                    k = number(c)
                    state, value = (b, k), score + channel + log_p[(a * SIZE + b) * SIZE + k]
                else:
                    state, value = (a, b), score + channel
                if state not in after or value > after[state]:
                    after[state], back[state] = value, ((a, b), c)
        states = after
        steps.append(back)
        if len(steps) >= due:
            pasts = [traced(steps, s)[1] for s in states]
            same = next((k for k, at in enumerate(zip(*pasts, strict=True)) if len(set(at)) == 1), None)
            if same is not None:  # all ways lead through one state, `same` + 1 steps back
                cut = len(steps) - same - 1
                settled += reversed(traced(steps[:cut], pasts[0][same])[0])
                steps = steps[cut:]
            due = 2 * max(SETTLE, len(steps))
    state = max(states, key=lambda s: (states[s] + log_p[(s[0] * SIZE + s[1]) * SIZE + EDGE], s))
    return "".join((*settled, *reversed(traced(steps, state)[0])))


#: Strength from which a word is telling.
STRONG = 3.0


def parted(word: str, known: dict[str, float], lengths: list[int]) -> str:
    """A reading without known borders, cut before and after the telling words in it; the longest at each place."""
    out, at, start = [], 0, 0
    while at < len(word):
        n = next((n for n in lengths if len(word) >= at + n and known.get(word[at : at + n], 0.0) >= STRONG), 0)
        if n:
            out += [word[start:at], word[at : at + n]]
            start = at + n
        at += n or 1
    return " ".join(x for x in (*out, word[start:]) if x)


class Restorer:
    """Restores texts under one model; readings of short spans are remembered, up to a bound.

    Separators between all letters hide where words end, so such a reading is cut at `known` words.
    """

    def __init__(self, log_p: np.ndarray, known: dict[str, float] | None = None):
        lengths = sorted({len(w) for w, x in (known or {}).items() if x >= STRONG and len(w) > 3 and w.isalpha()}, reverse=True)

        def fresh(span: str) -> str:
            said = decode(span, log_p)
            if not known or all(c.isalpha() or c in LEET for c in span):
                return said
            return WORD.sub(lambda m: m[0] if m[0] in known else parted(m[0], known, lengths), said)

        self.log_p = log_p
        remembered = lru_cache(maxsize=100_000)(fresh)
        self.read = lambda span: (remembered if len(span) <= REMEMBERED else fresh)(span)

    def __call__(self, text: str) -> str:
        text = folded(text)
        return SUSPECT.sub(lambda m: self.read(m[0]) if any(c.isalpha() for c in m[0]) else m[0], text) if _QUICK.search(text) else text


# --- weights ----------------------------------------------------------------------------------------


def parts(word: str) -> Iterator[str]:
    """Features of a word: itself, and its beginnings."""
    yield word
    for n in (4, 5, 6):
        if len(word) > n:
            yield f"{word[:n]}-"


def strengths(rows: list[tuple[str, int, int]], n1: int, n0: int) -> dict[str, float]:
    """Log odds of features (name, toxic documents with it, others with it) that lean clearly to toxic ones."""
    most: dict[str, int] = {}  # of the words with a beginning, the documents of the commonest
    for name, a, _ in rows:
        for p in parts(name) if not name.endswith("-") else ():
            if p != name:
                most[p] = max(most.get(p, 0), a)
    out = {}
    for name, a, b in rows:
        if name.endswith("-") and a < 2 * most.get(name, 0):
            continue  # says no more than that word
        expected = (a + b) * n1 / max(1, n1 + n0)
        if a >= LEAST_SEEN and (a - expected) / math.sqrt(max(expected * n0 / max(1, n1 + n0), 1e-9)) >= LEAST_Z:
            out[name] = math.log((a + 0.5) / (n1 + 1)) - math.log((b + 0.5) / (n0 + 1))
    return dict(sorted(out.items(), key=lambda x: (-x[1], x[0])))


def evidence(text: str | None, restore: Restorer, weights: dict[str, float]) -> tuple[float, float, float, float]:
    """Strongest, second strongest, and number of telling words; telling words for each hundred."""
    if not text:
        return 0.0, 0.0, 0.0, 0.0
    known = WORD.findall(restore(text))
    found: list[float] = []
    get = weights.get
    for w in known:
        if (x := get(w)) is not None:
            found.append(x)
        elif len(w) > 4:
            best = max((get(f"{w[:n]}-", 0.0) for n in (4, 5, 6) if len(w) > n), default=0.0)
            if best > 0:
                found.append(best)
    found.sort(reverse=True)
    strong = sum(x >= STRONG for x in found)
    return found[0] if found else 0.0, found[1] if len(found) > 1 else 0.0, math.log1p(strong), min(5.0, 100 * strong / len(known)) if known else 0.0


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Model:
    """Learns labels from rows outside the held-out fold only."""
    counts = corpus_trigrams(docs)
    rows, known = labelled_sample(docs, labels, "toxic", fold("doc_id", 3) != 1, per_class)
    rows = rows.withColumn("half", F.pmod(F.xxhash64(F.lit("half"), "doc_id"), F.lit(2)).cast("int"))
    plain = language_model(counts, {})
    share = (known.get(1, 0) + 0.5) / (sum(known.values()) + 1)
    flat = Model(plain, {}, (0.0, 0.0, 0.0, 0.0, math.log(share / (1 - share))))
    if not known.get(0) or not known.get(1):
        return flat

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, list[int]] = {"": [0] * 4}
        restore = Restorer(plain)
        for part in row_batches(batches):
            for y, half, text in zip(part.column("y").to_pylist(), part.column("half").to_pylist(), part.column("text").to_pylist(), strict=True):
                for f in {"", *(f for w in set(WORD.findall(restore(text))) for f in parts(w))}:
                    seen.setdefault(f, [0] * 4)[2 * half + y] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(seen)), *(pa.array([v[k] for v in seen.values()], pa.int64()) for k in range(4))], names=["f", "b0", "a0", "b1", "a1"])

    summed = rows.mapInArrow(features, "f string, b0 long, a0 long, b1 long, a1 long").groupBy("f").agg(*(F.sum(c).alias(c) for c in ("b0", "a0", "b1", "a1")))
    # words that several documents of a bounded sample hold, and of these only what leans to toxic ones
    lean = min(known[1], per_class) / min(known[0], per_class)
    found = summed.where(f"f = '' or (a0 + a1 >= {LEAST_SEEN} and a0 + a1 > 2 * {lean} * (b0 + b1))").orderBy("f").collect()
    total = next((r for r in found if r["f"] == ""), None)
    if total is None:  # labels, but none of a document that is here
        return flat

    def learned(*halves: int) -> dict[str, float]:
        of = lambda r, c: sum(r[f"{c}{h}"] for h in halves)
        return strengths([(r["f"], of(r, "a"), of(r, "b")) for r in found if r["f"]], of(total, "a"), of(total, "b"))

    weights, other = learned(0, 1), (learned(1), learned(0))
    log_p = language_model(counts, {w: x for w, x in weights.items() if not w.endswith("-")})

    def measure(batch: pa.RecordBatch) -> dict:
        restore = [Restorer(log_p, w) for w in other]
        # a half is measured with what the other one taught
        e = np.array([evidence(t, restore[h], other[h]) for t, h in zip(batch.column("text").to_pylist(), batch.column("half").to_pylist(), strict=True)]).reshape(-1, 4)
        return {"y": batch.column("y")} | {f"x{k}": e[:, k] for k in range(4)}

    x = np.array(sorted(map(tuple, map_rows(rows, measure, "y int, x0 double, x1 double, x2 double, x3 double").collect()))).reshape(-1, 5)
    if len(set(x[:, 0])) < 2:
        return flat
    return Model(log_p, weights, tuple(map(float, logistic(x[:, 1:], x[:, 0], penalty=0.5, weight=prior_weights(x[:, 0], known)))))


def score(texts: list[str | None], model: Model, restore: Restorer | None = None) -> np.ndarray:
    restore = restore or Restorer(model.log_p, model.weights)
    x = np.array([evidence(t, restore, model.weights) for t in texts]).reshape(-1, 4)
    return sigmoid(x @ np.array(model.calibration[:-1]) + model.calibration[-1])


def score_column(model: Model, text: str = "text") -> Column:
    """The score as a column: only texts travel to Python, all other columns stay where they are."""

    @F.pandas_udf("double")
    def scores(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        restore = Restorer(model.log_p, model.weights)
        for part in parts:
            yield pd.Series(np.concatenate([score(list(part.iloc[at : at + ROWS_AT_ONCE]), model, restore) for at in range(0, len(part), ROWS_AT_ONCE)] or [np.zeros(0)]))

    return scores(F.col(text))


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, per_class: int = PER_CLASS) -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""
    model = train(docs, labels, per_class)
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold("doc_id", 3) == 1).alias("held_out"), score_column(model).alias("score"))
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def without_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, per_class: int = PER_CLASS) -> DataFrame:
    """Docs, with all their columns, of a score below the threshold."""
    return docs.withColumn("__toxic", score_column(train(docs, labels, per_class))).where(F.col("__toxic") < threshold).drop("__toxic")
