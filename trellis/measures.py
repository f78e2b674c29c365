"""Cost, replication and balance measures, and the experiments that chart them."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import baselines
from .adapt.engine import Engine
from .adapt.tree import POLICIES
from .operators.evaluate import Options, Traffic, distributed
from .plans.cost import Case, plan_order
from .plans.patterns import BGP
from .sources.store import Store, balance, place_by, seeds, store_of
from .sources.vocab import CORE, triples_from_tables
from .workloads import FAMILIES, TEMPLATES, TRAINING, Slots, div_workload, template, uni_workload

WORKERS = 8
LOCALITY = {"none": Options(locality=False, pinning=False), "locality": Options(pinning=False), "both": Options()}


def response_time(df: DataFrame) -> float:
    """Seconds until all rows are made, and thrown away."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def communication(store: Store, bgp: BGP, options: Options | None = None) -> Traffic:
    traffic = Traffic()
    distributed(store, bgp, options, traffic)
    return traffic


def synchronisations(store: Store, bgp: BGP) -> int:
    """Joins of a plan that workers must wait for each other in."""
    store.refine_all(bgp)
    return sum(c in (Case.HASH, Case.BROADCAST) for c in plan_order(bgp, store.knowledge, store.workers).state.cases)


def work_balance(store: Store, bgp: BGP) -> DataFrame:
    """(home, rows): what each worker produced of an answer; homes without rows too."""
    every = store.spark.range(1).select(F.explode(F.array(*map(F.lit, seeds(store.workers)))).alias("home"))
    return every.join(distributed(store, bgp).groupBy("home").agg(F.count("*").alias("rows")), "home", "left").na.fill(0, ["rows"])


def touched(store: Store, bgps: list[BGP]) -> tuple[int, int]:
    """Distinct triples that the patterns of a workload match, and all triples."""
    parts = None
    for p in dict.fromkeys(p for b in bgps for p in b):
        one = store.scan(p).select("s", "p", "o")
        parts = one if parts is None else parts.union(one)
    return parts.distinct().count(), store.total


def placed_balance(store: Store, engine: Engine) -> DataFrame:
    """Balance of stored triples, replicas included, after a workload."""
    placed = store.spark.table(store.ps).select("home")
    for m in engine.index.modules.values():
        if m.table:
            placed = placed.union(store.spark.table(m.table).select("home"))
    return balance(placed, store.workers)


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def locality_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys and values moved by the seven, and their answers' seconds, using no property of the placement, hashing, or also pinning."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    for name in (f"uni_l{k}" for k in range(1, 8)):
        for variant, options in LOCALITY.items():
            t = communication(store, template(name), options)
            rows.append((name, variant, t.keys, t.values, t.total, response_time(distributed(store, template(name), options))))
    return _frame(spark, rows, "query string, variant string, keys long, moved_values long, total long, seconds double")


def with_family_means(runs: DataFrame) -> DataFrame:
    """Runs (family, variant, ms) with the geometric mean of their family and variant, as the runtime tables have it."""
    return runs.withColumn("family_mean", F.exp(F.avg(F.log(F.greatest(F.col("ms"), F.lit(0.001)))).over(Window.partitionBy("family", "variant"))))


#: The runtime tables: by family, all their templates.
TABLES = {"UNI": tuple(f"uni_l{k}" for k in range(1, 8)), **{f"DIV {f}": tuple(FAMILIES[f]) for f in "LSFC"}, "ENC": tuple(f"enc_y{k}" for k in range(1, 5)), "LIF": tuple(f"lif_b{k}" for k in range(1, 6))}


def runtimes(spark: SparkSession, sf_dir: str, families: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """Milliseconds of whole answers in the distributed and the adaptive mode, with the geometric means of families."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    for family, names in (families or TABLES).items():
        for name in names:
            bgp = template(name)
            store.refine_all(bgp)
            fixed, adaptive = Engine(store, adaptive=False), Engine(store, threshold=1, budget=50.0).train([bgp])
            for variant, engine in (("fixed", fixed), ("adaptive", adaptive)):
                out, mode = engine.answer(bgp)
                rows.append((family, name, variant, mode, 1000 * response_time(out)))
            del out, adaptive
    return with_family_means(_frame(spark, rows, "family string, query string, variant string, mode string, ms double"))


def baseline_runtimes(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("uni_l3", "uni_l4", "uni_l6")) -> DataFrame:
    """Milliseconds of the comparison systems over the whole graph, beside the engine without adaptivity."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    for name in names:
        bgp = template(name)
        store.refine_all(bgp)
        rows.append((name, "engine", 1000 * response_time(Engine(store, adaptive=False).answer(bgp)[0])))
        for kind in baselines.KINDS:
            began = time.perf_counter()
            out = baselines.answer(store, kind, bgp)  # stages that are written belong to the time
            out.write.format("noop").mode("overwrite").save()
            rows.append((name, kind, 1000 * (time.perf_counter() - began)))
    return _frame(spark, rows, "query string, system string, ms double")


def startup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of mapping, of placing by each way, and of the replicating baselines, over the whole graph, without dictionaries."""
    triples = triples_from_tables(spark, sf_dir, CORE).select("s", "p", "o")
    rows = [("map", response_time(triples))]
    rows += [(f"place by {how}", response_time(place_by(triples, how, WORKERS))) for how in ("subject", "object", "random")]
    rows.append(("2-hop replication", response_time(baselines.khop(triples, 2, WORKERS))))
    rows.append(("min-cut", response_time(baselines.min_cut(triples, WORKERS))))
    return _frame(spark, rows, "phase string, seconds double")


def initial_replication(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stored triples beyond the originals, over the whole graph: none here, k-hop replicas, and cut edges of a min-cut partition."""
    store = store_of(spark, sf_dir, WORKERS)
    n = store.total
    rows = [("subject hash", n, 0.0)]
    for name, kind in (("2-hop forward", "khop"), ("2-hop by name prefix", "khop_prefix")):
        r = baselines.replication(baselines.prepared(store, kind), n).first()
        rows.append((name, r["stored"], float(r["ratio"])))
    cut = baselines.edge_cut(baselines.triples_of(store), baselines.prepared(store, "summary")).first()
    rows.append(("min-cut", n + cut["cut"], float(cut["ratio"])))
    return _frame(spark, rows, "placement string, stored long, ratio double")


def _played(engine: Engine, queries: list[tuple[str, BGP]]) -> list[tuple]:
    """A workload's rows of `PLAYED`: cumulative seconds of whole answers and of the redistribution after them, and values sent by both.

    What queries send is counted apart from the time.
    """
    total_s, total_t, rows = 0.0, 0, []
    for k, (name, bgp) in enumerate(queries):
        began = time.perf_counter()
        engine.run(bgp, sink=True)
        total_s += time.perf_counter() - began
        run = engine.log[-1]
        if run.mode == "distributed":
            run.traffic = communication(engine.store, bgp, engine.options).total
        total_t += run.traffic + run.sent
        rows.append((k, name, run.mode, total_s, total_t, run.sent, run.replicas, run.made, run.evicted))
    return rows


PLAYED = "k int, query string, mode string, seconds double, moved long, sent_by_redistribution long, replicas long, made int, evicted int"


def drift(spark: SparkSession, sf_dir: str, n: int = 24, threshold: int = 3, budget: float = 0.2) -> DataFrame:
    """One family after the other: cumulative seconds and values moved, adaptive and not, under a budget."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    queries = div_workload(n, "CFSL", mixed=False, slots=Slots.of(store))
    for variant, engine in (("fixed", Engine(store, adaptive=False)), ("adaptive", Engine(store, threshold=threshold, budget=budget))):
        rows += [(variant, *r) for r in _played(engine, queries)]
    return _frame(spark, rows, f"variant string, {PLAYED}")


def threshold_sweep(spark: SparkSession, sf_dir: str, n: int = 24, thresholds: tuple[int, ...] = (1, 5, 10)) -> DataFrame:
    """Seconds, values moved and replicas at the end of a workload of each kind, by frequency threshold."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    slots = Slots.of(store)
    for kind, queries in (("UNI", uni_workload(n, seed=3, slots=slots)), ("DIV", div_workload(n, seed=3, slots=slots))):
        for t in thresholds:
            played = _played(Engine(store, threshold=t, budget=5.0), queries)
            last = played[-1]
            rows.append((kind, t, n, last[3], last[4], last[6], last[6] / store.total, sum(r[2] in ("parallel", "star", "empty") for r in played)))
    return _frame(spark, rows, "workload string, threshold int, queries int, seconds double, moved long, replicas long, ratio double, parallel int")


def tree_policies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replicas, data touched and modules by the order in which trees are grown."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    queries = [template(x) for x in ("uni_q02", "uni_q08", "uni_q11", "div_f1", "div_f2")]
    for policy in POLICIES:
        began = time.perf_counter()
        engine = Engine(store, threshold=1, budget=50.0, policy=policy).train(queries)
        parallel = sum(engine.mode(b)[0] in ("parallel", "star") for b in queries)
        rows.append((policy, engine.index.replicas, engine.index.moved, len(engine.index.modules), parallel, time.perf_counter() - began))
    return _frame(spark, rows, "policy string, replicas long, touched long, modules int, parallel int, seconds double")


def trained_pairs(spark: SparkSession, sf_dir: str, n: int = 6, training: int = 16) -> DataFrame:
    """A mixed workload after training on two families and freezing, and with adaptation instead."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    slots = Slots.of(store)
    test = div_workload(n, seed=11, slots=slots)
    for pair in (*TRAINING, "adaptive"):
        engine = Engine(store, threshold=2, budget=5.0)
        if pair != "adaptive":
            engine.train([b for _, b in div_workload(training, pair, seed=5, slots=slots)]).freeze()
        *_, last = _played(engine, test)
        rows.append((pair, last[3], last[4], last[6], sum(r.mode in ("parallel", "star", "empty") for r in engine.log)))
    return _frame(spark, rows, "training string, seconds double, moved long, replicas long, parallel int")


def load_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples by worker after a workload, as shares, with the replication ratio."""
    store = store_of(spark, sf_dir, WORKERS)
    engine = Engine(store, threshold=2, budget=5.0).train([b for _, b in div_workload(24, seed=2, slots=Slots.of(store))])
    return placed_balance(store, engine).withColumn("replication", F.lit(engine.index.replicas / store.total))


def workload_balance(spark: SparkSession, sf_dir: str, n: int = 16) -> DataFrame:
    """(home, rows, share): what each worker produced of the answers of an adaptive workload."""
    store = store_of(spark, sf_dir, WORKERS)
    engine, total = Engine(store, threshold=3, budget=5.0), dict.fromkeys(seeds(WORKERS), 0)
    for _, bgp in uni_workload(n, slots=Slots.of(store)):
        for r in engine.answer(bgp)[0].groupBy("home").count().collect():  # a row for each worker
            total[r["home"]] += r["count"]
        engine.observe(bgp)
    every = max(1, sum(total.values()))
    return _frame(spark, [(h, k, k / every) for h, k in total.items()], "home int, rows long, share double")


def answer_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return work_balance(store_of(spark, sf_dir, WORKERS), template("uni_q02"))


#: A simple and a complex query of those that scaling is shown with.
SCALED = ("uni_l4", "uni_l6", "uni_l1")


def strong_scaling(spark: SparkSession, sf_dir: str, workers: tuple[int, ...] = (2, 4, 8, 16)) -> DataFrame:
    """The same data on more workers: milliseconds without and with adaptivity, the largest share of a worker, and the values moved."""
    rows = []
    for w in workers:
        store = store_of(spark, sf_dir, w)
        for name in SCALED:
            t = communication(store, template(name))
            share = work_balance(store, template(name)).agg((F.max("rows") / F.greatest(F.lit(1), F.sum("rows"))).alias("m")).first()["m"]
            rows.append((w, name, *both_ways(store, name), float(share), t.total))
    return _frame(spark, rows, "workers int, query string, fixed_ms double, adaptive_ms double, largest_share double, moved long")


def both_ways(store: Store, name: str) -> tuple[float, float]:
    """Milliseconds of a template without and with adaptivity."""
    bgp = template(name)
    store.refine_all(bgp)
    engines = (Engine(store, adaptive=False), Engine(store, threshold=1, budget=50.0).train([bgp]))
    return tuple(1000 * response_time(e.answer(bgp)[0]) for e in engines)


def data_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed workers, growing data: the given folder's tables and those of the smaller folders beside it."""
    parent, _, own = sf_dir.rstrip("/").rpartition("/")
    scales = [x for x in (0.001, 0.01, 0.1) if own == f"sf{x}" or (own.startswith("sf") and x < float(own[2:]))] if own[2:].replace(".", "").isdigit() else []
    rows = []
    for folder in [f"{parent}/sf{x}" for x in scales] or [sf_dir]:
        store = store_of(spark, folder, WORKERS)
        for name in SCALED:
            rows.append((folder.rpartition("/")[2], store.total, name, *both_ways(store, name)))
    return _frame(spark, rows, "data string, triples long, query string, fixed_ms double, adaptive_ms double")


def plan_syncs(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = store_of(spark, sf_dir, WORKERS)
    return _frame(spark, [(x, synchronisations(store, template(x))) for x in TEMPLATES], "query string, distributed_joins int")


def workload_reach(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of all triples that the patterns of each family's templates match."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    for family, names in TABLES.items():
        some, all_of = touched(store, [template(x) for x in names])
        rows.append((family, some, all_of, some / all_of))
    return _frame(spark, rows, "family string, touched long, triples long, share double")


def uni_mix(spark: SparkSession, sf_dir: str, n: int = 16) -> DataFrame:
    """A sample of the pool of fourteen templates, played adaptively."""
    store = store_of(spark, sf_dir, WORKERS)
    return _frame(spark, _played(Engine(store, threshold=3, budget=1.0), uni_workload(n, slots=Slots.of(store))), PLAYED)


Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {f"measure_{n}": f for n, f in {
    "locality": locality_ablation, "runtimes": runtimes, "baseline_runtimes": baseline_runtimes, "startup": startup, "initial_replication": initial_replication, "drift": drift, "threshold": threshold_sweep,
    "policies": tree_policies, "training": trained_pairs, "balance_after": load_balance, "answer_balance": answer_balance, "work_balance": workload_balance, "strong_scaling": strong_scaling, "data_scaling": data_scaling, "synchronisation": plan_syncs,
    "reach": workload_reach, "uni_mix": uni_mix,
}.items()}
ORACLE_SQL: dict[str, str] = {}
