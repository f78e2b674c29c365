"""Functions written in Python, for Arrow batches, and their registration for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship


def iri_kind(spark: SparkSession):
    """The part of a name before its slash; null where there is none."""
    ship(spark)

    @F.pandas_udf("string")
    def kind(names: pd.Series) -> pd.Series:
        parts = names.str.partition("/")
        return parts[0].where(parts[1] == "/")

    return kind


def majority_candidates(df: DataFrame, key: str, value: str) -> DataFrame:
    """(key, candidate): majority vote in constant space.

    Votes are made in each task over its own rows and merged by key, so that a hot key is a few
    partial votes and not all its rows; the candidate is confirmed by counting.
    """
    ship(df.sparkSession)

    def votes(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        state: dict = {}
        for part in parts:
            for (k, v), n in part.groupby([key, value]).size().items():
                c, lead = state.get(k, (v, 0))
                state[k] = (c, lead + n) if c == v else (c, lead - n) if lead >= n else (v, n - lead)
        yield pd.DataFrame([(k, c, n) for k, (c, n) in state.items()], columns=["key", "candidate", "lead"])

    kinds = dict(df.dtypes)
    part = df.select(key, value).mapInPandas(votes, f"key {kinds[key]}, candidate {kinds[value]}, lead long")
    return part.select("key", "candidate").distinct()


def majority_vote(df: DataFrame, key: str, value: str) -> DataFrame:
    """(key, majority): the value of more than half of a key's rows, null where there is none.

    A value with a majority over all rows has one in some task's rows, so partial candidates are
    enough; one exact count of candidates decides.
    """
    seen = df.groupBy(key).agg(F.count("*").alias("n"))
    counted = df.join(majority_candidates(df, key, value).select(F.col("key").alias(key), F.col("candidate").alias(value)), [key, value], "left_semi").groupBy(key, value).agg(F.count("*").alias("k"))
    best = counted.join(seen, key).where(F.col("k") * 2 > F.col("n")).select(key, F.col(value).alias("majority"))
    return seen.select(key).join(best, key, "left")


class PatternEdges:
    """Table function: the triple patterns of a query text."""

    def eval(self, text: str):
        from trellis.plans.parser import ParseError, parse

        try:
            for p in parse(text).bgp:
                yield str(p.s), str(p.p), str(p.o)
        except ParseError:
            return


def register(spark: SparkSession, engine=None) -> None:
    """Makes the functions callable from SQL; `graph_match_view` makes a view of a query's answers."""
    ship(spark)
    spark.udf.register("iri_kind", iri_kind(spark))
    spark.udtf.register("pattern_edges", F.udtf(PatternEdges, returnType="s string, p string, o string"))


def graph_match_view(engine, name: str, text: str) -> None:
    """A temporary view of a query's answers, for use in SQL."""
    engine.run(text).createOrReplaceTempView(name)
