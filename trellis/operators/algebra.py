"""Operators around pattern answers: joins of all kinds, windows, top-k, sets, paths. All take and give DataFrames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import checkpointed


def join(left: DataFrame, right: DataFrame, on: list[str], strategy: str = "auto", how: str = "inner") -> DataFrame:
    """Equi-join; `strategy` forces broadcast, shuffle_hash or merge. Broadcasting is for sides of a known bound."""
    hints = {"auto": None, "broadcast": "broadcast", "shuffle_hash": "shuffle_hash", "merge": "merge"}
    return left.join(right.hint(hints[strategy]) if hints[strategy] else right, on, how)


def exists(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right, on, "left_semi")


def minus(left: DataFrame, right: DataFrame) -> DataFrame:
    """Rows without a compatible one on the right; without shared columns nothing is removed."""
    shared = [c for c in left.columns if c in right.columns]
    return left.join(right, shared, "left_anti") if shared else left


def range_join(points: DataFrame, at: str, intervals: DataFrame, lo: str, hi: str, width: float) -> DataFrame:
    """Points within [lo, hi): both sides meet in bins of a width, then the ends are compared."""
    binned = intervals.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    met = points.withColumn("__bin", F.floor(F.col(at) / width)).join(binned, "__bin")
    return met.where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("__bin")


def interval_join(left: DataFrame, right: DataFrame, key: str, left_at: str, right_at: str, before: float, after: float) -> DataFrame:
    """Pairs of a key whose right time lies from `before` to `after` beyond the left one, met in bins as wide as that."""
    width = before + after
    wide = left.withColumn("__bin", F.explode(F.sequence(F.floor((F.col(left_at) - before) / width), F.floor((F.col(left_at) + after) / width))))
    return wide.join(right.withColumn("__bin", F.floor(F.col(right_at) / width)), [key, "__bin"]).where((F.col(right_at) >= F.col(left_at) - before) & (F.col(right_at) <= F.col(left_at) + after)).drop("__bin")


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, direction: str = "backward", tolerance: float | None = None) -> DataFrame:
    """For each left row the right value of the latest time not after it (or earliest not before it): one union, one sort."""
    both = left.select(*[F.col(c) for c in left.columns], F.lit(1).alias("__left"), F.lit(None).cast(right.schema[value].dataType).alias("__value"), F.lit(None).cast(right.schema[at].dataType).alias("__when"))
    other = right.select(*[F.col(c) if c in (key, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.lit(0).alias("__left"), F.col(value).alias("__value"), F.col(at).alias("__when"))
    back = direction == "backward"
    order = [F.col(at).asc() if back else F.col(at).desc(), F.col("__left").asc()]
    w = Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    found = F.last(F.when(F.col("__left") == 0, F.struct("__value", "__when")), ignorenulls=True).over(w)
    out = both.unionByName(other).withColumn("__f", found).where("__left = 1")
    good = F.lit(True) if tolerance is None else F.abs(F.col(at) - F.col("__f.__when")) <= tolerance
    return out.withColumn(f"asof_{value}", F.when(good, F.col("__f.__value"))).select(*left.columns, f"asof_{value}")


def salted_join(big: DataFrame, small: DataFrame, on: str, salts: int = 8) -> DataFrame:
    """A join whose hot keys are dealt out: the big side draws a salt, the small one is there for each."""
    left = big.withColumn("__salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    return left.join(small.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>"))), [on, "__salt"]).drop("__salt")


def top_k(df: DataFrame, k: int, by: list[Column], per: list[str]) -> DataFrame:
    return df.withColumn("__rn", F.row_number().over(Window.partitionBy(*per).orderBy(*by))).where(F.col("__rn") <= k).drop("__rn")


def edges_of(triples: DataFrame, predicate: str) -> DataFrame:
    return triples.where(F.col("p") == predicate).select("s", "o")


def path_sequence(a: DataFrame, b: DataFrame) -> DataFrame:
    """(s, o) of a then b."""
    return a.select("s", F.col("o").alias("m")).join(b.select(F.col("s").alias("m"), "o"), "m").select("s", "o").distinct()


def path_alternative(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.union(b).distinct()


def path_inverse(a: DataFrame) -> DataFrame:
    return a.select(F.col("o").alias("s"), F.col("s").alias("o"))


def path_bounded(a: DataFrame, least: int, most: int) -> DataFrame:
    """Distinct pairs joined by `least` to `most` edges."""
    out, step = None, a.distinct()
    for n in range(1, most + 1):
        if n > 1:
            step = path_sequence(step, a)
        if n >= least:
            out = step if out is None else out.union(step)
    return out.distinct()


def path_closure(a: DataFrame, reflexive: bool = False, most: int = 10_000) -> DataFrame:
    """Transitive closure: only what was new last is joined on; each round is cut into the shared folder."""
    edges = checkpointed(a.select("s", "o").distinct())
    found = new = edges
    for _ in range(most):
        new = checkpointed(path_sequence(new, edges).join(found, ["s", "o"], "left_anti"))
        if new.isEmpty():
            break
        found = checkpointed(found.union(new))
    if reflexive:
        ends = edges.select(F.explode(F.array("s", "o")).alias("s"))
        found = found.union(ends.select("s", F.col("s").alias("o"))).distinct()
    return found


def neighbourhood(triples: DataFrame, start: DataFrame, hops: int, direction: str = "forward") -> DataFrame:
    """Triples within so many hops of the start vertices (column v)."""
    reached, out = start.select("v").distinct(), None
    for _ in range(hops):
        part = triples.join(reached.withColumnRenamed("v", "s"), "s", "left_semi")
        if direction == "both":
            part = part.union(triples.join(reached.withColumnRenamed("v", "o"), "o", "left_semi"))
        out = part if out is None else out.union(part)
        ends = part.select(F.explode(F.array("s", "o") if direction == "both" else F.array("o")).alias("v"))
        reached = reached.union(ends).distinct()
    return out.distinct()
