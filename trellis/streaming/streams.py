"""Streaming operators over events, query logs and triples; every one also works on a batch."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..adapt.engine import Engine
from ..adapt.heatmap import heat_from_log, path_of, path_text
from ..adapt.tree import build_tree, vertex_scores
from ..plans.parser import ParseError, parse
from ..session import shared_folder, ship
from ..sources.store import Store, home


def read_stream(spark: SparkSession, sf_dir: str, table: str, files: int = 1) -> DataFrame:
    """A table's files as a stream, so many at a time; timestamps with the session's zone."""
    batch = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    place = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{table}.parquet")
    folder = place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory()
    reader = spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", files)
    source = reader.parquet(f"{sf_dir}/{table}.parquet") if folder else reader.option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    return source.withColumns({f.name: F.col(f.name).cast("timestamp") for f in batch.schema if f.dataType.typeName() == "timestamp_ntz"})


def finished(stream: DataFrame, mode: str = "append", keep: str | None = None) -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote: each batch to a folder of its own, so a repeated batch replaces itself."""
    spark = stream.sparkSession
    at = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.schema(stream.schema).option("basePath", f"{at}/out").parquet(f"{at}/out") if _exists(spark, f"{at}/out") else spark.createDataFrame([], stream.schema)
    if mode == "complete" and "batch" in out.columns:
        last = out.agg(F.max("batch")).first()[0]
        out = out.where(F.col("batch") == last)
    return out.drop("batch")


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def tumbling(events: DataFrame, width: str, watermark: str | None = None) -> DataFrame:
    return _windowed(events, F.window("ts", width), watermark)


def sliding(events: DataFrame, width: str, slide: str, watermark: str | None = None) -> DataFrame:
    return _windowed(events, F.window("ts", width, slide), watermark)


def session(events: DataFrame, gap: str, watermark: str | None = None) -> DataFrame:
    source = events.withWatermark("ts", watermark) if watermark else events
    return source.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def _windowed(events: DataFrame, window, watermark: str | None) -> DataFrame:
    source = events.withWatermark("ts", watermark) if watermark else events
    return source.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def deduplicated(events: DataFrame, key: str, delay: str) -> DataFrame:
    """One event for each key within the watermark's delay; state is kept no longer."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def with_static(events: DataFrame, facts: DataFrame, key: str, name: str) -> DataFrame:
    """New events against stored facts (s, o): the pattern `?event byUser ?user . ?user p ?o`, continuously."""
    return events.join(facts.select(F.col("s").alias(key), F.col("o").alias(name)), key)


def followed(first: DataFrame, second: DataFrame, key: str, within: str, delay: str) -> DataFrame:
    """Pairs of two streams' events of one key, the second within so long after the first; both sides' state is bounded."""
    a = first.withWatermark("ts", delay).select(F.col(key), F.col("ts").alias("a"), F.col("event_id").alias("first"))
    b = second.withWatermark("ts", delay).select(F.col(key).alias("__k"), F.col("ts").alias("b"), F.col("event_id").alias("second"))
    return a.join(b, F.expr(f"{key} = __k and b >= a and b <= a + interval {within}")).select(key, "first", "second")


def counted_by_state(paths: DataFrame, idle_ms: int | None = None) -> DataFrame:
    """(path, n): running counts in keyed state; with `idle_ms`, a path that isn't seen for so long is forgotten."""
    ship(paths.sparkSession)

    def count(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n = (state.get[0] if state.exists else 0) + sum(len(p) for p in parts)
        state.update((n,))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({"path": [key[0]], "n": [n]})

    return paths.groupBy("path").applyInPandasWithState(count, "path string, n long", "n long", "update", GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.ProcessingTimeTimeout)


def tree_paths(log: DataFrame, engine: Engine) -> DataFrame:
    """(qid, ts, path, child_const) of every tree edge of the log's queries, under the engine's frozen scores."""
    ship(log.sparkSession)
    stats, rule, policy = engine.store.stats, engine.rule(), engine.policy

    def edges(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            rows = []
            for q, ts, text in part[["qid", "ts", "text"]].itertuples(index=False):
                try:
                    bgp = parse(text).bgp
                    tree = build_tree(bgp, vertex_scores(bgp, stats, policy), **rule)
                except (ParseError, ValueError):
                    continue
                met = tree.constants()
                rows += [(q, ts, path_text(p), c) for p in tree.paths for c in met.get(p, (None,))]
            yield pd.DataFrame(rows, columns=["qid", "ts", "path", "child_const"])

    return log.select("qid", "ts", "text").mapInPandas(edges, "qid long, ts timestamp, path string, child_const string")


def heat_batch(log: DataFrame, engine: Engine) -> list:
    """(path, cnt, consts, last_used) rows of a batch of queries: a row for each path of their trees."""
    return heat_from_log(tree_paths(log, engine)).collect()


def monitor(log: DataFrame, engine: Engine, name: str = "log", checkpoint: str | None = None) -> Engine:
    """Feeds a stream of queries to the heat map: counted by path in each batch, then merged, detected and redistributed.

    The heat map remembers the batches that it holds, by the stream's name, so a batch that is
    delivered again counts once.
    """

    def merge(batch: DataFrame, number: int) -> None:
        if (name, number) in engine.heat.batches:
            return
        rows = heat_batch(batch, engine)
        engine.heat.merge(((path_of(r["path"]), r["cnt"], r["consts"] or {}) for r in rows), (name, number))
        engine.adapt()

    at = checkpoint or f"{shared_folder(log.sparkSession)}/monitor-{uuid.uuid4().hex}"
    log.writeStream.foreachBatch(merge).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
    return engine


def ingest(triples: DataFrame, store: Store, path: str) -> DataFrame:
    """Appends a stream of triples, placed by subject, in folders by batch number: a batch that is repeated replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        placed = batch.select(home("s", store.workers).alias("home"), "s", "p", "o").distinct()
        placed.repartition(store.workers, "home").write.mode("overwrite").parquet(f"{path}/batch={number}")

    triples.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}_state").trigger(availableNow=True).start().awaitTermination()
    return store.spark.read.option("basePath", path).parquet(path).drop("batch")
