"""Registered streaming queries: batch twins with oracles, and streams run over what is there."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..adapt.engine import Engine
from ..session import shared_folder
from ..sources.store import store_of
from ..sources.vocab import triples_from_tables
from ..workloads import query_text, template
from . import streams as S


def _batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    return e.withColumn("ts", F.col("ts").cast("timestamp"))


def _plain(df: DataFrame) -> DataFrame:
    """Times without zone, as the files have them."""
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c, k in df.dtypes if k == "timestamp"})


def tumbling(spark, sf_dir):
    return _plain(S.tumbling(_batch(spark, sf_dir), "1 day"))


def sliding(spark, sf_dir):
    return _plain(S.sliding(_batch(spark, sf_dir), "2 days", "1 day"))


def session(spark, sf_dir):
    return _plain(S.session(_batch(spark, sf_dir), "6 hours"))


def tumbling_stream(spark, sf_dir):
    return _plain(S.finished(S.tumbling(S.read_stream(spark, sf_dir, "events"), "1 day", "40 days"), "complete"))


def dedup_stream(spark, sf_dir):
    return S.finished(S.deduplicated(S.read_stream(spark, sf_dir, "events"), "event_id", "40 days").select("event_id"))


def late_stream(spark, sf_dir):
    """Windows closed by the watermark, in append mode."""
    return _plain(S.finished(S.tumbling(S.read_stream(spark, sf_dir, "events"), "1 day", "1 hour")))


def static_join_stream(spark, sf_dir):
    facts = triples_from_tables(spark, sf_dir, ("locatedIn",))
    events = S.read_stream(spark, sf_dir, "events").withColumn("user", F.concat(F.lit("customer/"), "user_id"))
    return S.finished(S.with_static(events, facts, "user", "nation").select("event_id", "nation"))


def stream_join_stream(spark, sf_dir):
    events = lambda kind: S.read_stream(spark, sf_dir, "events").where(F.col("event_type") == kind)
    return S.finished(S.followed(events("view"), events("purchase"), "user_id", "1 day", "40 days"))


def _log(spark: SparkSession) -> str:
    path = f"{shared_folder(spark)}/log-{uuid.uuid4().hex}"
    names = ["uni_q02"] * 3 + ["div_f2"] * 2 + ["uni_q11"] * 4
    rows = [(k, query_text(template(x))) for k, x in enumerate(names)]
    log = spark.createDataFrame(rows, "qid long, text string").withColumn("ts", F.timestamp_seconds(F.lit(1_700_000_000) + F.col("qid") * 60))
    log.write.parquet(path)
    return path


def heat_stream(spark, sf_dir):
    """Paths and counts of a monitored query log, and which of them were redistributed."""
    engine = Engine(store_of(spark, sf_dir), threshold=3, budget=50.0)
    log = spark.readStream.schema("qid long, text string, ts timestamp").parquet(_log(spark))
    S.monitor(log, engine)
    from ..adapt.heatmap import path_text

    return spark.createDataFrame([(path_text(p), n.count, p in engine.index.modules) for p, n in engine.heat.walk()], "path string, cnt int, redistributed boolean")


def state_stream(spark, sf_dir):
    engine = Engine(store_of(spark, sf_dir))
    log = spark.readStream.schema("qid long, text string, ts timestamp").parquet(_log(spark))
    return S.finished(S.counted_by_state(S.tree_paths(log, engine)), "update")


def ingest_stream(spark, sf_dir):
    events = S.read_stream(spark, sf_dir, "events").select(F.concat(F.lit("event/"), "event_id").alias("s"), F.lit("kind").alias("p"), F.concat(F.lit("kind/"), "event_type").alias("o"))
    placed = S.ingest(events, store_of(spark, sf_dir), f"{shared_folder(spark)}/ingest-{uuid.uuid4().hex}")
    return placed.groupBy("o").agg(F.count("*").alias("n"))


QUERIES = {f"st_{f.__name__}": f for f in (tumbling, sliding, session, tumbling_stream, dedup_stream, late_stream, static_join_stream, stream_join_stream, heat_stream, state_stream, ingest_stream)}
_DAILY = "select date_trunc('day', ts) :: timestamp as start, event_type, count(*) as n from events group by all"
ORACLE_SQL = {
    "st_tumbling": _DAILY,
    "st_tumbling_stream": _DAILY,
    "st_sliding": "select d.start, event_type, count(*) as n from events, (select unnest([date_trunc('day', ts) :: timestamp, date_trunc('day', ts) :: timestamp - interval 1 day]) as start, event_id as k from events) as d where event_id = k and ts >= d.start and ts < d.start + interval 2 day group by all",
    "st_late_stream": "select date_trunc('day', ts) :: timestamp as start, event_type, count(*) as n from events where date_trunc('day', ts) + interval 1 day <= (select max(ts) from events) - interval 1 hour group by all",
    "st_session": "with g as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 6 hour or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events), n as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, min(ts) as start, max(ts) + interval 6 hour as \"end\", count(*) as n from n group by user_id, k",
    "st_dedup_stream": "select distinct event_id from events",
    "st_static_join_stream": "select event_id, concat('nation/', c_nationkey) as nation from events join customer on user_id = c_custkey",
    "st_stream_join_stream": "select a.user_id, a.event_id as first, b.event_id as second from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 day",
    "st_ingest_stream": "select concat('kind/', event_type) as o, count(*) as n from events group by 1",
}
