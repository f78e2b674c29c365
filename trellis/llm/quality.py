"""Quality by compression: dictionaries of good and of bad labelled text.

A text is cut into blocks; each block is compressed on its own with a dictionary made of good
text, with one made of bad text and with none. The difference of the two sums, over the sum
without dictionary, says which of the two kinds the text shares more with. A logistic
calibration on other labelled rows, with the plain compression ratio and the length beside it,
makes it a probability.

Labels come from a bounded sample (`PER_CLASS` documents of each class, chosen by a hash of the
id): half of it fills the dictionaries, half calibrates. Scoring reads whole texts.

Nulls: a null text is an empty one and gets the score that calibration gives zero bytes. With
labels of one class only, or none, every score is the smoothed share of label 1. Repeated rows
get equal scores; a score at the threshold counts as good. Texts of any length are read whole,
block by block.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard as zstd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, labelled_sample, logistic, map_rows, prior_weights, sigmoid

#: Labelled documents taken of each class.
PER_CLASS = 2000
#: Bytes that are compressed on their own. Whole texts are covered, block by block.
BLOCK = 4096
#: Bytes of one dictionary, and those that one labelled document adds to it at most.
DICTIONARY, PIECE = 110 << 10, 1024
LEVEL = 3


@dataclass(frozen=True)
class Model:
    good: bytes
    bad: bytes
    weights: tuple[float, ...]


@lru_cache(maxsize=4)
def _compressors(good: bytes, bad: bytes):
    make = lambda d: zstd.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False) if d else zstd.ZstdCompressor(level=LEVEL, write_content_size=False)
    dicts = []
    for raw in (good, bad):
        d = zstd.ZstdCompressionDict(raw, dict_type=zstd.DICT_TYPE_RAWCONTENT) if raw else None
        if d is not None:
            d.precompute_compress(level=LEVEL)
        dicts.append(d)
    return [make(d) for d in (*dicts, None)]


def sizes(text: str | None, good: bytes, bad: bytes) -> tuple[int, int, int, int]:
    """Bytes of the text, and compressed with the good, the bad and no dictionary."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    blocks = [raw[at : at + BLOCK] for at in range(0, len(raw), BLOCK)]
    return (len(raw), *(sum(len(c.compress(b)) for b in blocks) for c in _compressors(good, bad)))


def features(s: np.ndarray) -> np.ndarray:
    """Normalised difference, ratio, and length, from rows of sizes()."""
    n, good, bad, plain = np.asarray(s, float).reshape(-1, 4).T
    base = np.maximum(plain, 1)
    return np.column_stack([10 * (bad - good) / base, 4 * plain / np.maximum(n, 1), np.log1p(n) / 4, 10 * np.minimum(good, bad) / base])


def dictionary(cuts: list[str]) -> bytes:
    """The same number of bytes from each cut of a text, up to DICTIONARY."""
    each = max(64, min(PIECE, DICTIONARY // max(1, len(cuts))))
    return b"".join(c.encode("utf-8", "surrogatepass")[:each] for c in cuts)[:DICTIONARY]


def constant(counts: dict[int, int]) -> Model:
    """The model of labels that don't tell classes apart: the smoothed share of label 1."""
    share = (counts.get(1, 0) + 0.5) / (sum(counts.values()) + 1)
    return Model(b"", b"", (0.0, 0.0, 0.0, 0.0, float(np.log(share / (1 - share)))))


def calibrate(good: bytes, bad: bytes, measured: np.ndarray, y: np.ndarray, counts: dict[int, int]) -> Model:
    return Model(good, bad, tuple(map(float, logistic(features(measured), y.astype(float), weight=prior_weights(y, counts)))))


def score(texts: list[str | None], model: Model) -> np.ndarray:
    x = features(np.array([sizes(t, model.good, model.bad) for t in texts], float).reshape(-1, 4))
    return sigmoid(x @ np.array(model.weights[:-1]) + model.weights[-1])


def train(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Model:
    """Learns from labelled rows outside the held-out fold only.

    What reaches the driver is bounded: PIECE bytes of each document for the dictionaries, then
    four sizes of each whole document of the other half.
    """
    rows, counts = labelled_sample(docs, labels, "quality", fold("doc_id", 5) != 0, per_class)
    half = F.pmod(F.xxhash64(F.lit("half"), "doc_id"), F.lit(2))
    at = F.pmod(F.xxhash64("text"), F.greatest(F.lit(1), F.length("text") - PIECE + 1)) + 1
    cuts = rows.where(half == 0).select("doc_id", "y", F.substring("text", at.cast("int"), F.lit(PIECE)).alias("cut")).collect()
    cuts.sort(key=lambda r: (r["doc_id"] * 0x9E3779B97F4A7C15 % (1 << 64), r["cut"]))
    good, bad = (dictionary([r["cut"] for r in cuts if r["y"] == c]) for c in (1, 0))
    if not good or not bad:
        return constant(counts)

    def work(batch: pa.RecordBatch) -> dict:
        s = np.array([sizes(t, good, bad) for t in batch.column("text").to_pylist()], np.int64).reshape(-1, 4)
        return {"y": batch.column("y"), "n": s[:, 0], "good": s[:, 1], "bad": s[:, 2], "plain": s[:, 3]}

    found = np.array(sorted(map(tuple, map_rows(rows.where(half == 1), work, "y int, n long, good long, bad long, plain long").collect()))).reshape(-1, 5)
    if len(set(found[:, 0])) < 2:
        return constant(counts)
    return calibrate(good, bad, found[:, 1:], found[:, 0], counts)


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, per_class: int = PER_CLASS) -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""
    model = train(docs, labels, per_class)

    def work(batch: pa.RecordBatch) -> dict:
        s = score(batch.column("text").to_pylist(), model)
        return {"doc_id": batch.column("doc_id"), "held_out": batch.column("held_out"), "score": s, "predicted": (s >= threshold).astype(np.int32)}

    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold("doc_id", 5) == 0).alias("held_out"), "text")
    return map_rows(given, work, "doc_id long, held_out boolean, score double, predicted int")
