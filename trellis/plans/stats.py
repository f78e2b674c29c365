"""Predicate statistics: cardinalities, distinct ends, degrees, scores, fan-outs, outliers."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most predicates whose statistics are brought to the driver.
MOST_PREDICATES = 200_000


@dataclass(frozen=True)
class Predicate:
    """What the planner knows of one predicate, or of one pattern with constants."""

    name: str
    card: int
    n_s: int
    n_o: int
    score_s: float = 0.0
    score_o: float = 0.0
    outlier: bool = False

    @property
    def p_ps(self) -> float:
        return self.card / self.n_s if self.n_s else 0.0

    @property
    def p_po(self) -> float:
        return self.card / self.n_o if self.n_o else 0.0


def _sent_home(rows: DataFrame, workers: int) -> DataFrame:
    from ..sources.store import home

    return rows.withColumn("home", home("v", workers)).repartition(workers, "home")


def vertex_degree(triples: DataFrame, workers: int | None = None) -> DataFrame:
    """(v, deg_in, deg_out, degree) of every subject and object; one aggregation over both ends.

    Triples that lie by the `home` of their subject on `workers` are counted there: only distinct
    objects travel, with their counts, to the home that they have as subjects.
    """
    if workers is not None:
        outs = triples.groupBy("home", F.col("s").alias("v")).agg(F.count("*").alias("outs"))
        ins = _sent_home(triples.groupBy(F.col("o").alias("v")).agg(F.count("*").alias("ins")), workers)
        both = outs.hint("merge").join(ins, ["home", "v"], "full").select("home", "v", F.coalesce("ins", F.lit(0)).alias("deg_in"), F.coalesce("outs", F.lit(0)).alias("deg_out"))
        return both.withColumn("degree", F.col("deg_in") + F.col("deg_out"))
    ends = triples.select(F.explode(F.array(F.struct(F.col("s").alias("v"), F.lit(0).alias("inward")), F.struct(F.col("o").alias("v"), F.lit(1).alias("inward")))).alias("x"))
    return ends.groupBy("x.v").agg(F.sum("x.inward").alias("deg_in"), F.sum(1 - F.col("x.inward")).alias("deg_out"), F.count("*").alias("degree"))


def predicate_statistics(triples: DataFrame, exact: bool = True, workers: int | None = None) -> DataFrame:
    """(p, card, n_s, n_o, score_s, score_o, p_ps, p_po): scores are mean degrees over distinct ends.

    Distinct ends of a predicate are pre-aggregated by (p, end), so a predicate or a hub with a
    large share of all triples is not gathered in one task. Inexact counts use sketches.
    """
    if workers is not None and exact:
        degree = vertex_degree(triples, workers).select("home", "v", "degree")

        def here(end: str) -> DataFrame:
            ends = triples.groupBy("p", *(["home"] if end == "s" else []), F.col(end).alias("v")).agg(F.count("*").alias("k"))
            ends = ends if end == "s" else _sent_home(ends, workers)
            return ends.hint("merge").join(degree, ["home", "v"]).groupBy("p").agg(F.sum("k").alias(f"card_{end}"), F.count("*").alias(f"n_{end}"), F.avg("degree").alias(f"score_{end}"))

        both = here("s").join(here("o"), "p").select("p", F.col("card_s").alias("card"), "n_s", "n_o", "score_s", "score_o")
        return both.withColumn("p_ps", F.col("card") / F.col("n_s")).withColumn("p_po", F.col("card") / F.col("n_o"))
    degree = vertex_degree(triples).select("v", "degree")

    def side(end: str) -> DataFrame:
        return triples.groupBy("p", F.col(end).alias("v")).agg(F.count("*").alias("k")).join(degree, "v").groupBy("p").agg(F.sum("k").alias(f"card_{end}"), F.count("*").alias(f"n_{end}"), F.avg("degree").alias(f"score_{end}"))

    if exact:
        both = side("s").join(side("o"), "p").select("p", F.col("card_s").alias("card"), "n_s", "n_o", "score_s", "score_o")
    else:
        both = triples.groupBy("p").agg(F.count("*").alias("card"), F.approx_count_distinct("s").alias("n_s"), F.approx_count_distinct("o").alias("n_o"))
        both = both.withColumns({"score_s": F.lit(None).cast("double"), "score_o": F.lit(None).cast("double")})
    return both.withColumn("p_ps", F.col("card") / F.col("n_s")).withColumn("p_po", F.col("card") / F.col("n_o"))


def statistics_by_home(placed: DataFrame) -> DataFrame:
    """(home, p, card, n_s, n_o): each worker's own statistics. n_s adds up over homes (a subject has one), n_o doesn't."""
    return placed.groupBy("home", "p").agg(F.count("*").alias("card"), F.count_distinct("s").alias("n_s"), F.count_distinct("o").alias("n_o"))


def collect_statistics(stats: DataFrame) -> dict[str, Predicate]:
    """To the driver: a row for each predicate, behind a check of their number."""
    rows = stats.limit(MOST_PREDICATES + 1).collect()
    if len(rows) > MOST_PREDICATES:
        raise ValueError(f"more than {MOST_PREDICATES} predicates")
    return {r["p"]: Predicate(r["p"], r["card"], r["n_s"], r["n_o"], r["score_s"] or 0.0, r["score_o"] or 0.0) for r in rows}


def chauvenet(values: dict[str, float], passes: int = 1, scale: str = "linear") -> set[str]:
    """Names of extremely high values: those of which fewer than half a one is expected so far out.

    The criterion is two-sided, only the high side is used; deviations are of the population.
    """
    out: set[str] = set()
    for _ in range(passes):
        kept = {k: math.log(v) if scale == "log" and v > 0 else v for k, v in values.items() if k not in out}
        n = len(kept)
        if n < 3:
            break
        mean = math.fsum(kept.values()) / n
        sd = math.sqrt(math.fsum((v - mean) ** 2 for v in kept.values()) / n)
        new = {k for k, v in kept.items() if sd > 0 and v > mean and n * math.erfc((v - mean) / (sd * math.sqrt(2))) < 0.5}
        if not new:
            break
        out |= new
    return out


def flag_outliers(stats: dict[str, Predicate], passes: int = 1, scale: str = "linear") -> dict[str, Predicate]:
    """Predicates of extreme subject scores, then, of the rest, of extreme object scores, are marked; both their scores fall."""
    by_s = chauvenet({k: v.score_s for k, v in stats.items()}, passes, scale)
    by_o = chauvenet({k: v.score_o for k, v in stats.items() if k not in by_s}, passes, scale)
    return {k: replace(v, score_s=-math.inf, score_o=-math.inf, outlier=True) if k in by_s | by_o else v for k, v in stats.items()}


def profile(triples: DataFrame, workers: int | None = None) -> DataFrame:
    """One row: triples, distinct ends and their overlap, predicates, and in- and out-degree means and deviations."""
    d = vertex_degree(triples, workers)
    ends = d.agg(
        F.sum("deg_out").alias("triples"), F.count_if(F.col("deg_out") > 0).alias("subjects"), F.count_if(F.col("deg_in") > 0).alias("objects"), F.count_if((F.col("deg_out") > 0) & (F.col("deg_in") > 0)).alias("both"),
        F.avg(F.when(F.col("deg_in") > 0, F.col("deg_in"))).alias("in_avg"), F.stddev_pop(F.when(F.col("deg_in") > 0, F.col("deg_in"))).alias("in_sd"),
        F.avg(F.when(F.col("deg_out") > 0, F.col("deg_out"))).alias("out_avg"), F.stddev_pop(F.when(F.col("deg_out") > 0, F.col("deg_out"))).alias("out_sd"),
    )
    return ends.join(triples.agg(F.count_distinct("p").alias("predicates")))
