"""What the training-data operators share: reading, durable cuts, bounded samples, components.

Rows are never assumed to have unique or non-null ids. Column clashes are avoided by
selecting the input columns an operator needs under private names before anything else.
"""

from __future__ import annotations

import gc
import math
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import checkpointed, shared_folder, ship, shuffles_freed

#: Rows that a Python operator holds decoded at once; texts are whole, so this bounds memory by rows.
ROWS_AT_ONCE = 256


#: Rows of one Arrow batch: whole texts travel in it, so this bounds a worker's memory.
ARROW_ROWS = 1000


def ready(spark: SparkSession) -> None:
    """The package on the executors, and Arrow batches of bounded row count (a run-time setting)."""
    ship(spark)
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name, "10000")) <= ARROW_ROWS:
        spark.conf.set(name, str(ARROW_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ready(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let_go(spark: SparkSession) -> None:
    """Frees what finished steps hold: handles of long expressions at the driver, and, with them, shuffle files and broadcasts."""
    gc.collect()
    spark._jvm.System.gc()


def written(df: DataFrame, *more: DataFrame) -> DataFrame:
    """The rows as a table in the shared folder: made once, compressed, and read by column.

    Several parts of one schema are written one after the other; each one's shuffle files go when it is there.
    """
    path = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    for part in (df, *more):
        with shuffles_freed(df.sparkSession):
            part.write.mode("append").parquet(path)
    return df.sparkSession.read.parquet(path)


def removed(table: DataFrame) -> None:
    """Deletes the files of a table that `written` made and nothing reads any more."""
    spark = table.sparkSession
    for folder in {f.rpartition("/")[0] for f in table.inputFiles()}:
        old = spark._jvm.org.apache.hadoop.fs.Path(folder)
        old.getFileSystem(spark._jsc.hadoopConfiguration()).delete(old, True)


#: Columns that name a row.
KEYS = ["__file", "__row"]


def row_keys(docs: DataFrame) -> DataFrame:
    """Docs with two columns that name a row in the same way each time it is read.

    Rows of files are named by file and position, which don't depend on how a scan is split;
    other tables are first cut into the shared folder.
    """
    try:
        named = docs.withColumn("__file", F.xxhash64(F.col("_metadata.file_path"))).withColumn("__row", F.col("_metadata.row_index"))
        named.schema  # noqa: B018  analysis fails here where there is no such metadata
        return named
    except AnalysisException:
        return checkpointed(docs.withColumn("__file", F.lit(0).cast("long")).withColumn("__row", F.monotonically_increasing_id()))


def row_batches(batches: Iterator[pa.RecordBatch], rows: int = ROWS_AT_ONCE) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def map_rows(df: DataFrame, work: Callable[[pa.RecordBatch], dict], schema: str, rows: int = ROWS_AT_ONCE) -> DataFrame:
    """mapInArrow over slices of bounded row count; `work` returns {column: values} in schema order."""
    ready(df.sparkSession)
    types = pa.schema([(f.name, _arrow(f.dataType)) for f in _fields(df, schema)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in row_batches(batches, rows):
            out = work(part)
            yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in types], schema=types)

    return df.mapInArrow(run, schema)


def _fields(df: DataFrame, schema: str):
    from pyspark.sql.types import StructType

    return StructType.fromDDL(schema).fields


def _arrow(kind) -> pa.DataType:
    from pyspark.sql.pandas.types import to_arrow_type

    return to_arrow_type(kind)


def fold(key: str, modulus: int) -> Column:
    """crc32 of the key's text, modulo; null keys count as remainder 0."""
    return F.coalesce(F.pmod(F.crc32(F.col(key).cast("string").cast("binary")), F.lit(modulus)), F.lit(0)).cast("int")


def hash_share(per_class: int, counts: dict, by: str, *of: str) -> Column:
    """Condition that keeps about `per_class` rows of each value of `by`, chosen by a hash of `of`.

    The choice depends on the rows alone, so a retried task keeps the same ones.
    """
    place = F.pmod(F.xxhash64(*[F.col(c) for c in of]), F.lit(1 << 30)) / F.lit(float(1 << 30))
    keep = F.lit(False)
    for value, n in counts.items():
        keep = keep | ((F.col(by) == F.lit(value)) & (place < F.lit(per_class / max(n, 1))))
    return keep


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, usable: Column, per_class: int) -> tuple[DataFrame, dict[int, int]]:
    """(doc_id, y, text), cut into the shared folder, and all labelled ids by class.

    At most about `per_class` labelled documents of each of the classes 0 and 1 are kept. The chosen
    ids are a bounded table (2 x per_class, 3 deviations of slack at most), so the documents meet
    them in a broadcast join and their texts are never shuffled. Texts are whole. An id whose labels
    contradict each other teaches nothing; of several documents of one id the least text counts.
    """
    given = labels.where(usable & F.col(label).isin(0, 1) & F.col("doc_id").isNotNull()).select("doc_id", F.col(label).cast("int").alias("y"))
    known = given.groupBy("doc_id").agg(F.min("y").alias("y"), F.max("y").alias("other")).where("y = other").select("doc_id", "y")
    counts = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    chosen = known.where(hash_share(per_class, counts, "y", "doc_id")).limit(2 * per_class + 6 * math.isqrt(2 * per_class))
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "y").agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))
    return checkpointed(rows), counts


def logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1e-2, rounds: int = 60, weight: np.ndarray | None = None) -> np.ndarray:
    """Ridge-penalised logistic regression by damped Newton steps; the last coefficient is the intercept."""
    x = np.hstack([np.asarray(x, float), np.ones((len(x), 1))])
    w, ridge = np.zeros(x.shape[1]), np.full(x.shape[1], penalty)
    ridge[-1] = 1e-6
    weight = np.ones(len(x)) if weight is None else weight

    def loss(w: np.ndarray) -> float:
        z = x @ w
        return float(weight @ (np.logaddexp(0, z) - y * z) + ridge @ (w * w) / 2)

    now = loss(w)
    for _ in range(rounds):
        p = sigmoid(x @ w)
        step = np.linalg.solve((x * (weight * p * (1 - p))[:, None]).T @ x + np.diag(ridge + 1e-9), x.T @ (weight * (y - p)) - ridge * w)
        size = 1.0
        while size > 1e-6 and loss(w + size * step) > now:
            size /= 2
        w = w + size * step
        before, now = now, loss(w)
        if before - now < 1e-9 * max(1.0, now):
            break
    return w


def prior_weights(y: np.ndarray, counts: dict[int, int]) -> np.ndarray:
    """Weights that give a balanced sample the class shares of all labelled rows."""
    total = max(1, sum(counts.values()))
    share = {c: counts.get(c, 0) / total for c in (0, 1)}
    own = {c: max(1, int((y == c).sum())) / max(1, len(y)) for c in (0, 1)}
    return np.array([share[int(c)] / own[int(c)] for c in y])


def sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root): the least node reachable from each node of the undirected edges.

    Alternating star contraction: a step hangs every larger neighbour of a node under the least
    of its neighbourhood, then every node under its least smaller neighbour, until nothing
    changes. Minima are pre-aggregated, so a hub is never gathered in one task; each step is cut
    into the shared folder. Rounds grow with the logarithm of the component size.
    """
    e = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    e, before = checkpointed(e), None
    while True:
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("x")).select("x.u", "x.v").where("u != v").distinct()
        e = checkpointed(small)
        now = e.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if tuple(now) == before:
            return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
        before = tuple(now)


#: A key is hot if it has more than one in so many of all rows; so there are fewer hot keys than that.
HOT = 1024


def spread_join(rows: DataFrame, one: DataFrame, key: str, counts: DataFrame | None = None) -> DataFrame:
    """Inner join with a table that has one row for each key, however many rows share a key.

    Rows of hot keys stay where they are and meet the fewer than `HOT` rows of `one` for them, which
    are broadcast; all others meet by the key's hash. `counts`: (key, n) of the rows, if known.
    """
    counts = written(rows.groupBy(key).agg(F.count("*").alias("n")).where("n > 1") if counts is None else counts.select(key, "n"))
    total = counts.agg(F.sum("n")).first()[0] or 0
    hot = written(one.join(F.broadcast(counts.where(F.col("n") > total / HOT).select(key)), key))
    cold = rows.join(F.broadcast(hot.select(key)), key, "left_anti").join(one, key)
    return rows.join(F.broadcast(hot), key).unionByName(cold)


def rank_in_key(rows: DataFrame, key: str, part: str, local: str, out: str) -> DataFrame:
    """Add `out`: a gapless rank (from 0) of each row within `key`, given (part, local) ranks.

    `local` ranks a row within (part, key). Only counts by (part, key) are summed over a key's
    parts, so no key's rows meet in one task however many it has.
    """
    counts = rows.groupBy(part, key).agg(F.count("*").alias("__n"))
    base = counts.select(part, key, (F.sum("__n").over(Window.partitionBy(key).orderBy(part).rowsBetween(Window.unboundedPreceding, 0)) - F.col("__n")).alias("__base"))
    return rows.join(base, [part, key]).withColumn(out, F.col("__base") + F.col(local)).drop("__base")
