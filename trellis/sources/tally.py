"""Statistics of the whole graph from the tables themselves: every row is counted where it lies, nothing is placed."""

from __future__ import annotations

import re
import uuid
from collections import defaultdict
from collections.abc import Iterable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.stats import Predicate
from ..session import shared_folder, shuffles_freed
from .vocab import NUMBERS, UNIQUE, Mapping, Star, prefix_of, star_groups, stars_of

#: Objects of a subject from which rows are compared as wholes, instead of being made distinct for each predicate.
WIDE = 3


def used(source: DataFrame, *expressions: str) -> list[str]:
    """The columns that expressions are made of."""
    return [c for c in source.columns if re.search(rf"\b{re.escape(c)}\b", " ".join(expressions))]


def tally(spark: SparkSession, sf_dir: str, mappings: Iterable[Mapping]) -> dict[str, Predicate]:
    """Cardinalities, distinct ends and mean degrees of all predicates, as `predicate_statistics` has them of the placed triples.

    A vertex's row tells its degree, and by a bit each of which predicates it is a subject or an
    object. Vertices that only one table's rows can name are summed up there and then.
    """
    mappings = list(mappings)
    names = list(dict.fromkeys(m.predicate for m in mappings))
    if len(names) > 63:
        raise ValueError("more predicates than a number has bits")
    bit = {p: F.lit(1 << k).cast("bigint") for k, p in enumerate(names)}
    number = {p: k for k, p in enumerate(names)}
    nothing = F.lit(0).cast("bigint")
    folder = f"{shared_folder(spark)}/tally-{uuid.uuid4().hex}"
    alone: dict[int, list[int]] = defaultdict(lambda: [0, 0])  # by the bits of subjects: vertices that are met nowhere else, and their degrees

    def keep(rows: DataFrame) -> None:
        """Appends (v, degree, as_s, as_o, p): p of objects' rows, whose degrees add up to a predicate's triples."""
        with shuffles_freed(spark):
            rows.select("v", F.col("degree").cast("bigint").alias("degree"), "as_s", "as_o", "p").write.mode("append").option("compression", "zstd").parquet(folder)

    def objects(rows: DataFrame, o: str, p: str, weight: int = 1) -> DataFrame:
        """Rows of objects: raw columns are grouped, and names are made of the groups."""
        n = rows.groupBy(*used(rows, o)).agg((F.count("*") * weight).alias("degree")).where("degree != 0")
        return n.select(F.expr(o).alias("v"), "degree", nothing.alias("as_s"), bit[p].alias("as_o"), F.lit(number[p]).alias("p")).where("v is not null")

    def ends(pairs: DataFrame, p: str, s: str, o: str, subject: str, object_: str) -> DataFrame:
        """Rows of both ends of distinct pairs, counted by two columns of one type, of which names are made by expressions of these columns."""
        both = pairs.select(F.explode(F.array(F.struct(F.col(s).alias("v"), F.lit(False).alias("inward")), F.struct(F.col(o).alias("v"), F.lit(True).alias("inward")))).alias("x"))
        n = both.groupBy("x.v", "x.inward").agg(F.count("*").alias("degree"))
        inward = F.col("inward")
        name = F.when(inward, F.expr(object_)).otherwise(F.expr(subject))
        return n.withColumns({s: F.col("v"), o: F.col("v")}).select(name.alias("v"), "degree", F.when(inward, nothing).otherwise(bit[p]).alias("as_s"), F.when(inward, bit[p]).otherwise(nothing).alias("as_o"), F.when(inward, number[p]).otherwise(-1).alias("p"))

    def distinct_ends(star: Star, m: Mapping, o: str) -> DataFrame:
        rows = star.source.where(f"({star.subject}) is not null and ({o}) is not null")
        keys = [used(rows, x) for x in (star.subject, o)]
        whole = dict(rows.dtypes)
        # names of one whole number each are as distinct as these
        if all(re.fullmatch(r"concat\('[^']*', (\w+)\)", x) and whole[k[0]] in ("int", "bigint") for x, k in zip((star.subject, o), keys, strict=True)) and keys[0] != keys[1]:
            (a,), (b,) = keys
            return ends(rows.select(F.col(a).cast("bigint").alias(a), F.col(b).cast("bigint").alias(b)).distinct(), m.predicate, a, b, star.subject, o)
        return ends(rows.select(F.expr(star.subject).alias("s"), F.expr(o).alias("o")).distinct(), m.predicate, "s", "o", "s", "o")

    def given(star: Star) -> Column:
        """Of a row: by a bit each, which of its objects there are."""

        def there(o: str) -> Column:
            if re.fullmatch(r"concat\([\w',/# -]*\)", o):  # null where one of its columns is, which is told without making the name
                return reduce(Column.__and__, [F.col(c).isNotNull() for c in used(star.source, o)], F.lit(True))
            return F.expr(f"({o}) is not null")

        return reduce(Column.bitwiseOR, [F.when(there(o), F.lit(1 << k).cast("bigint")).otherwise(nothing) for k, o in enumerate(star.objects)])

    def of_predicates(ms: list[Mapping]) -> Column:
        """The predicates' bits of a row's."""
        return reduce(Column.bitwiseOR, [F.when(F.col("given").bitwiseAND(F.lit(1 << k).cast("bigint")) != 0, bit[m.predicate]).otherwise(nothing) for k, m in enumerate(ms)])

    groups = star_groups(mappings)
    stars = stars_of(spark, sf_dir, mappings)
    own = _met_nowhere_else(mappings, groups, stars)
    small: list[DataFrame] = []
    subjects: list[str] = []
    for ((table, subject), ms), star in zip(groups.items(), stars, strict=True):
        rows = star.source.where(f"({subject}) is not null")
        named = rows.select(F.expr(subject).alias("v"), given(star).alias("given"), F.xxhash64(F.lit(0), *used(rows, *star.objects)).alias("h")).where("given != 0")
        degree, as_s = F.bit_count("given").cast("bigint").alias("degree"), of_predicates(ms).alias("as_s")
        if table in UNIQUE:
            if own[table, subject]:
                with shuffles_freed(spark):
                    for r in named.groupBy("given").agg(F.count("*").alias("n")).select("n", degree, as_s).collect():  # as many rows as objects can be missing
                        alone[r["as_s"]][0] += r["n"]
                        alone[r["as_s"]][1] += r["n"] * r["degree"]
            else:
                small.append(named.select("v", degree, as_s, nothing.alias("as_o"), F.lit(-1).alias("p")))
            small += [objects(rows, o, m.predicate) for o, m in zip(star.objects, ms, strict=True)]
        elif len(ms) < WIDE:
            for o, m in zip(star.objects, ms, strict=True):
                keep(distinct_ends(star, m, o))
        else:
            # subjects whose rows are all alike have one object each; of the others, rows are made distinct
            one = named.repartition("v").groupBy("v").agg(F.min("h").alias("least"), F.max("h").alias("most"), F.first("given").alias("given"))
            mixed = F.col("least") != F.col("most")
            path = f"{folder}-subjects-{len(subjects)}"
            subjects.append(path)
            key = F.when(mixed, F.col("v")) if own[table, subject] else F.col("v")
            with shuffles_freed(spark):
                one.select(key.alias("v"), mixed.alias("mixed"), "given").groupBy("v", "mixed", "given").agg(F.count("*").alias("n")).select("v", "mixed", "n", degree, as_s).write.option("compression", "zstd").parquet(path)
            told = spark.read.parquet(path)
            if own[table, subject]:
                for r in told.where("v is null").collect():
                    alone[r["as_s"]][0] += r["n"]
                    alone[r["as_s"]][1] += r["n"] * r["degree"]
            else:
                keep(told.where("not mixed").select("v", "degree", "as_s", nothing.alias("as_o"), F.lit(-1).alias("p")))
            keep(reduce(DataFrame.union, [objects(rows, o, m.predicate) for o, m in zip(star.objects, ms, strict=True)]))
            several = told.where("mixed").select(F.col("v").alias("s"))
            if not several.isEmpty():
                again = rows.withColumn("__s", F.expr(subject)).join(several, F.col("__s") == F.col("s"), "left_semi")
                for o, m in zip(star.objects, ms, strict=True):
                    distinct = again.select(F.col("__s").alias("s"), F.expr(o).alias("o")).where("o is not null").distinct()
                    keep(objects(again, o, m.predicate, -1).unionByName(ends(distinct, m.predicate, "s", "o", "s", "o")))
    if small:
        keep(reduce(DataFrame.union, small))
    met = spark.read.parquet(folder)
    with shuffles_freed(spark):
        card = {names[r["p"]]: r["n"] for r in met.where("p >= 0").groupBy("p").agg(F.sum("degree").alias("n")).collect()}
    vertices = met.groupBy("v").agg(F.sum("degree").alias("degree"), F.expr("bit_or(as_s)").alias("as_s"), F.expr("bit_or(as_o)").alias("as_o"))
    kinds = vertices.groupBy("as_s", "as_o").agg(F.count("*").alias("n"), F.sum("degree").alias("degree"))
    bits_of = F.array(*[F.struct(F.lit(k).alias("p"), F.lit(end).alias("end"), (F.col(end).bitwiseAND(F.lit(1 << k).cast("bigint")) != 0).alias("is")) for k in range(len(names)) for end in ("as_s", "as_o")])
    sums = kinds.select("n", "degree", F.explode(bits_of).alias("x")).where("x.is").groupBy("x.p", "x.end").agg(F.sum("n").alias("n"), F.sum("degree").alias("degree"))
    found: dict[tuple[str, str], list[int]] = defaultdict(lambda: [0, 0])
    with shuffles_freed(spark):
        for r in sums.collect():
            found[names[r["p"]], r["end"]] = [r["n"], r["degree"]]
    where = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = where.getFileSystem(spark._jsc.hadoopConfiguration())
    for x in (folder, *subjects):
        fs.delete(spark._jvm.org.apache.hadoop.fs.Path(x), True)
    for bits, (n, degrees) in alone.items():
        for k, p in enumerate(names):
            if bits >> k & 1:
                found[p, "as_s"][0] += n
                found[p, "as_s"][1] += degrees
    mean = lambda x: x[1] / x[0] if x[0] else 0.0
    return {p: Predicate(p, n, found[p, "as_s"][0], found[p, "as_o"][0], mean(found[p, "as_s"]), mean(found[p, "as_o"])) for p, n in card.items() if n}


def _met_nowhere_else(mappings: list[Mapping], groups: dict[tuple[str, str], list[Mapping]], stars: list[Star]) -> dict[tuple[str, str], bool]:
    """Of a table's subjects, whether neither another table's nor any object can be one; objects of which nothing is known are looked at."""
    alike = lambda a, b: a.startswith(b) or b.startswith(a)
    own: dict[tuple[str, str], bool] = {}
    for key in groups:
        prefix = prefix_of(key[1])
        others = [prefix_of(k[1]) for k in groups if k != key] + [known for m in mappings if m.kind not in NUMBERS and (known := prefix_of(m.object))]
        own[key] = "/" in prefix and not any(alike(prefix, x) for x in others)
    asked = {key: prefix_of(key[1]) for key, alone in own.items() if alone}
    open_ended = [(star, o) for star, ms in zip(stars, groups.values(), strict=True) for o, m in zip(star.objects, ms, strict=True) if m.kind not in NUMBERS and not prefix_of(m.object)]
    if asked and open_ended:
        seen = [star.source.agg(*[F.count_if(F.expr(o).startswith(x)).alias(f"n{k}") for k, x in enumerate(asked.values())]) for star, o in open_ended]
        total = reduce(DataFrame.union, seen).agg(*[F.sum(f"n{k}").alias(f"n{k}") for k in range(len(asked))]).first()
        for k, key in enumerate(asked):
            own[key] = not total[f"n{k}"]
    return own
