"""The registered queries of the training-data operators, with production parameters."""

from __future__ import annotations

import json
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table


def tokenizer() -> tuple[str, str, tuple[tuple[str, int], ...]]:
    """Place of the tokenizer's ranks, its pre-tokenisation pattern and its added tokens: from the installed package."""
    import public_tokenizers

    with open(public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as file:
        added = tuple((x["content"], x["id"]) for x in json.load(file)["added_tokens"])
    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, added


def op1_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import classify

    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_noisy_channel_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import classify

    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack

    return pack(spark, table(spark, sf_dir, "documents"), *tokenizer())


def op4_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import surrogate_documents

    return surrogate_documents(table(spark, sf_dir, "documents"))


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .urls import judge, labelled_urls

    return judge(table(spark, sf_dir, "pages"), labelled_urls(spark))


def op6_language_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .langid import identify

    return identify(table(spark, sf_dir, "documents"))


def op7_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import simhash_classes

    return simhash_classes(table(spark, sf_dir, "documents"))


def op8_lossless_webp(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .webp import media_columns

    return media_columns(table(spark, sf_dir, "documents"))


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontam import contamination

    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_consistent_hash_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import shard_documents

    return shard_documents(spark, table(spark, sf_dir, "documents"))


# --- what SQL can express of the operators above, through the same operators


def llm_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Host, path and rule of every URL, without the model's verdict."""
    return op5_url_filter(spark, sf_dir).select("page_id", "host", "path", "rule")


def llm_media_payloads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes and digests of all payloads, as they are read back from the stored images."""
    return op8_lossless_webp(spark, sf_dir).select("doc_id", "n_bytes", "payload_bytes", "payload_sha256")


def llm_shard_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows, first and last slot of every shard, and the bytes of all."""
    rows = op10_consistent_hash_sharding(spark, sf_dir)
    total = Window.partitionBy(F.lit(1))
    by = rows.groupBy("shard").agg(F.count("*").alias("n"), F.count_distinct("slot").alias("slots"), F.min("slot").alias("first"), F.max("slot").alias("last"), F.sum("size").alias("bytes"))
    return by.withColumn("bytes", F.sum("bytes").over(total))  # a row for each shard


def _rules_sql() -> str:
    from .urls import LOWER, RULES, UPPER

    rules = ", ".join(f"('{r.host}', '{r.path}')" for r in RULES)
    return (
        f"with cut as (select page_id, case when contains(url, '://') then substr(url, strpos(url, '://') + 3) else '' end as rest from pages), "
        f"named as (select page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), '{UPPER}', '{LOWER}') as host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) as path from cut) "
        f"select page_id, host, path, (select r.host || r.path from (values {rules}) as r(host, path) where (n.host = r.host or ends_with(n.host, '.' || r.host)) and starts_with(n.path, r.path) order by length(r.host || r.path) desc limit 1) as rule from named as n"
    )


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_compression_quality, op2_noisy_channel_toxicity, op3_best_fit_packing, op4_pii_surrogates, op5_url_filter, op6_language_spans, op7_simhash_near_dedup, op8_lossless_webp, op9_benchmark_decontamination, op10_consistent_hash_sharding, llm_url_rules, llm_media_payloads, llm_shard_balance)}
ORACLE_SQL: dict[str, str] = {
    "llm_url_rules": _rules_sql(),
    "llm_media_payloads": "with t as (select doc_id, encode(coalesce(text, '')) as raw from documents), n as (select doc_id, raw, octet_length(raw) as n_bytes, greatest(1, (octet_length(raw) + 63) // 64) * 64 as payload_bytes from t) select doc_id, n_bytes, payload_bytes, sha256(raw || repeat('\\x00' :: blob, payload_bytes - n_bytes)) as payload_sha256 from n",
    "llm_shard_balance": "with t as (select count(*) as rows, sum(octet_length(encode(coalesce(text, ''))) + 8) :: bigint as bytes from documents), s as (select unnest(range(24)) :: int as shard), n as (select shard, rows // 24 + case when shard < rows % 24 then 1 else 0 end as n, bytes from t, s) select shard, n, n as slots, 0 :: bigint as first, n - 1 as last, bytes from n where n > 0",
}
