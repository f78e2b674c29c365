"""Terms and numbers: ids by hash with repair of collisions, encoding and decoding."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import checkpointed


def build_dictionary(triples: DataFrame) -> DataFrame:
    """(id, lex): a number for every distinct subject and object.

    Ids are hashes, so encoding needs no join; terms whose hash clashes are all but the first
    moved to numbers of their own, made from the term and its turn.
    """
    terms = triples.select(F.explode(F.array("s", "o")).alias("lex")).distinct().withColumn("id", F.xxhash64("lex"))
    turn = F.row_number().over(Window.partitionBy("id").orderBy("lex"))
    return terms.withColumn("turn", turn).select(F.when(F.col("turn") == 1, F.col("id")).otherwise(F.xxhash64("lex", "turn")).alias("id"), "lex")


def collisions(dictionary: DataFrame) -> DataFrame:
    """Terms that don't have their own hash as id; few or none."""
    return dictionary.where(F.col("id") != F.xxhash64("lex"))


def encode(triples: DataFrame, exceptions: DataFrame | None = None) -> DataFrame:
    """(s, p, o) with numbers at s and o: hashes, but for the exceptions' terms, which are joined."""
    out = triples.select(*[c for c in triples.columns if c not in "so"], F.xxhash64("s").alias("s"), F.xxhash64("o").alias("o"), F.col("s").alias("__s"), F.col("o").alias("__o"))
    if exceptions is not None:
        for c in "so":
            out = out.join(exceptions.select(F.col("lex").alias(f"__{c}"), F.col("id").alias("__id")), f"__{c}", "left").withColumn(c, F.coalesce("__id", c)).drop("__id")
    return out.drop("__s", "__o")


def decode(answers: DataFrame, dictionary: DataFrame, columns: list[str]) -> DataFrame:
    for c in columns:
        answers = answers.join(dictionary.select(F.col("id").alias(c), F.col("lex").alias(f"__{c}")), c).drop(c).withColumnRenamed(f"__{c}", c)
    return answers


def dense_dictionary(triples: DataFrame) -> DataFrame:
    """(id, lex) with ids from 0 without gaps, in order of the terms: counts by partition of a range sort give each its start."""
    terms = triples.select(F.explode(F.array("s", "o")).alias("lex")).distinct().orderBy("lex")
    # cut here: the bounds of a range sort may differ from one run to the next
    numbered = checkpointed(terms.withColumn("__m", F.monotonically_increasing_id()).withColumn("__part", F.shiftright("__m", 33)))
    base = numbered.groupBy("__part").agg(F.count("*").alias("n")).withColumn("base", F.sum("n").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n"))
    return numbered.join(F.broadcast(base.select("__part", "base")), "__part").select((F.col("base") + F.col("__m").bitwiseAND((1 << 33) - 1)).alias("id"), "lex")
