"""Triples and edges as files: N-Triples, CSV and JSON, with bad lines kept aside."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_folder
from .vocab import triples_from_tables

_LINE = r'^\s*<([^<>\s]*)>\s+<([^<>\s]*)>\s+(?:<([^<>\s]*)>|"((?:[^"\\]|\\.)*)"(?:\^\^<([^<>\s]*)>)?)\s*\.\s*(?:#.*)?$'
#: Kinds of objects and the names of their types in files.
TYPES = {"int": "integer", "dec": "decimal", "dbl": "double", "date": "date", "ts": "dateTime"}


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o, o_kind, _corrupt): IRIs, plain and typed literals; comments and empty lines are skipped."""
    lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#.*)?$"))
    good = F.col("value").rlike(_LINE)
    part = lambda k: F.regexp_extract("value", _LINE, k)
    literal = F.regexp_replace(F.regexp_replace(F.regexp_replace(part(4), r"\\n", "\n"), r'\\"', '"'), r"\\\\", r"\\")
    is_iri = part(3) != ""
    kind = F.lit("str")
    for k, t in TYPES.items():
        kind = F.when(part(5) == t, k).otherwise(kind)
    return lines.select(
        F.when(good, part(1)).alias("s"), F.when(good, part(2)).alias("p"), F.when(good, F.when(is_iri, part(3)).otherwise(literal)).alias("o"),
        F.when(good, F.when(is_iri, F.lit("iri")).otherwise(kind)).alias("o_kind"), F.when(~good, F.col("value")).alias("_corrupt"),
    )


def write_ntriples(triples: DataFrame, path: str) -> None:
    """Lines of (s, p, o, o_kind); literals are escaped, numbers and dates typed."""
    text = F.regexp_replace(F.regexp_replace(F.regexp_replace("o", r"\\", r"\\\\"), '"', r'\\"'), "\n", r"\\n")
    kind = F.lit("")
    for k, t in TYPES.items():
        kind = F.when(F.col("o_kind") == k, F.lit(f"^^<{t}>")).otherwise(kind)
    end = F.when(F.col("o_kind") == "iri", F.concat(F.lit("<"), "o", F.lit(">"))).otherwise(F.concat(F.lit('"'), text, F.lit('"'), kind))
    triples.select(F.concat(F.lit("<"), "s", F.lit("> <"), "p", F.lit("> "), end, F.lit(" .")).alias("value")).write.text(path)


def read_edges(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """CSV with a header, or JSON lines, under an explicit schema; what doesn't fit goes to _corrupt."""
    reader = spark.read.schema(f"{schema}, _corrupt string").option("columnNameOfCorruptRecord", "_corrupt").option("mode", "PERMISSIVE")
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)


def write_edges(df: DataFrame, path: str, fmt: str) -> None:
    (df.write.option("header", True).csv if fmt == "csv" else df.write.json)(path)


def _place(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/files-{uuid.uuid4().hex}"


def round_trip_ntriples(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _place(spark)
    write_ntriples(triples_from_tables(spark, sf_dir, ("label", "partOf", "locatedIn")), path)
    back = read_ntriples(spark, path)
    return back.where("_corrupt is null").groupBy("p").agg(F.count("*").alias("triples"))


def round_trip_csv(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _place(spark)
    write_edges(spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_custkey", "o_orderstatus"), path, "csv")
    return read_edges(spark, path, "csv", "o_orderkey long, o_custkey long, o_orderstatus string").groupBy(F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"))


def round_trip_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _place(spark)
    write_edges(spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_orderpriority"), path, "json")
    return read_edges(spark, path, "json", "o_orderkey long, o_orderpriority string").groupBy(F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("n"))
