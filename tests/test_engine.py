"""The engine on Spark: worked example, plan shapes, invariants, adaptivity, baselines, oracles."""

import pytest
from pyspark.sql import functions as F

from trellis.adapt.engine import Engine
from trellis.operators import algebra as A
from trellis.operators.evaluate import Options, Traffic, distributed, exchanges, plain_of, star
from trellis.plans.patterns import BGP, Pattern, Var
from trellis.plans.stats import predicate_statistics, vertex_degree
from trellis.sources.dictionary import build_dictionary, dense_dictionary, encode
from trellis.sources.store import balance, build, home, place_by, store_of
from trellis.workloads import template

CAMPUS = [
    ("James", "worksFor", "CS"), ("Bill", "worksFor", "CS"), ("Lisa", "advisor", "James"), ("Lisa", "advisor", "Bill"), ("John", "advisor", "Bill"), ("Fred", "advisor", "Bill"),
    ("Lisa", "uGradFrom", "MIT"), ("James", "uGradFrom", "CMU"), ("Bill", "uGradFrom", "CMU"), ("John", "uGradFrom", "CMU"), ("James", "gradFrom", "MIT"), ("Bill", "gradFrom", "CMU"),
    ("John", "type", "Grad"), ("Lisa", "type", "Grad"),
]


@pytest.fixture(scope="module")
def campus(spark):
    return build(spark, spark.createDataFrame(CAMPUS, "s string, p string, o string"), 2)


def same(a, b):
    b = b.select(*a.columns)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_campus_statistics(spark):
    t = spark.createDataFrame(CAMPUS, "s string, p string, o string")
    degree = {r["v"]: r["degree"] for r in vertex_degree(t).collect()}
    assert {k: degree[k] for k in ("Bill", "James", "Fred", "John", "Lisa")} == {"Bill": 6, "James": 4, "Fred": 1, "John": 3, "Lisa": 4}
    r = predicate_statistics(t).where("p = 'advisor'").first()
    assert (r["card"], r["n_s"], r["n_o"]) == (4, 3, 2)
    assert abs(r["score_s"] - 8 / 3) < 1e-9 and r["score_o"] == 5 and abs(r["p_ps"] - 4 / 3) < 1e-9 and r["p_po"] == 2


def test_campus_answers(campus):
    bgp = BGP.parse("?prof worksFor CS . ?stud advisor ?prof")
    want = {("James", "Lisa"), ("Bill", "John"), ("Bill", "Fred"), ("Bill", "Lisa")}
    for options in (Options(), Options(pinning=False), Options(locality=False, pinning=False), Options(broadcast_bytes=0)):
        got = distributed(campus, bgp, options).select("prof", "stud").collect()
        assert sorted(map(tuple, got)) == sorted(want)


def test_rows_stay_with_the_pinned_subject(campus):
    out = distributed(campus, BGP.parse("?stud advisor ?prof . ?prof worksFor CS . ?stud uGradFrom ?u"))
    homes = out.select("home", "stud", "prof", home("stud", 2).alias("a"), home("prof", 2).alias("b")).collect()
    assert homes and (all(r["home"] == r["a"] for r in homes) or all(r["home"] == r["b"] for r in homes))


def test_repeated_variable_and_disconnected(spark):
    store = build(spark, spark.createDataFrame([("a", "p", "a"), ("a", "p", "b")], "s string, p string, o string"), 2)
    assert [r["x"] for r in store.answer(Pattern(Var("x"), Var("q"), Var("x"))).collect()] == ["a"]
    with pytest.raises(ValueError):
        distributed(store, BGP.parse("?a p ?b . ?c p ?d"))
    assert distributed(store, BGP.parse("?a p ?b . ?c p ?d"), cross=True).count() == 4


def test_plan_shapes(spark, sf):
    store = store_of(spark, sf)
    assert exchanges(star(store, template("uni_q04"))) == 0
    engine = Engine(store, threshold=1, budget=50.0).train([template("uni_q02")])
    out, mode = engine.answer(template("uni_q02"))
    assert mode == "parallel" and exchanges(out) == 0
    assert same(out.drop("home"), plain_of(store, template("uni_q02")))


def test_locality_saves_communication(spark, sf):
    store = store_of(spark, sf)
    totals = {}
    for name, options in (("none", Options(locality=False, pinning=False)), ("locality", Options(pinning=False)), ("both", Options())):
        totals[name] = Traffic()
        distributed(store, template("uni_q11"), options, totals[name])
    assert totals["none"].total >= totals["locality"].total >= totals["both"].total


def test_adaptivity(spark, sf):
    store = store_of(spark, sf)
    engine = Engine(store, threshold=3, budget=50.0)
    bgp = template("uni_q11")
    for _ in range(4):
        out = engine.run(bgp, meter=True)
    assert [r.mode for r in engine.log] == ["distributed"] * 3 + ["parallel"]
    assert engine.log[-1].traffic == 0 and engine.log[2].made > 0
    assert same(out, plain_of(store, bgp))
    engine.index.evict(0)
    assert engine.index.replicas == 0 and engine.mode(bgp)[0] == "distributed"
    assert same(engine.answer(bgp)[0].drop("home"), plain_of(store, bgp))
    again = engine.restored([bgp] * 3)
    assert again.mode(bgp)[0] == "parallel"


def test_constants_restrict_modules(spark, sf):
    store = store_of(spark, sf)
    engine = Engine(store, threshold=1, budget=50.0).train([template("uni_q11")])
    other = BGP.parse("?x type class/Supplier . ?x basedIn ?z . ?z partOf region/2")
    assert engine.mode(other)[0] == "distributed"
    engine.observe(other)
    engine.observe(other)
    assert same(engine.answer(other)[0].drop("home"), plain_of(store, other))


def test_placement(spark, sf):
    t = spark.table(store_of(spark, sf).ps).select("s", "p", "o")
    rows = {how: balance(place_by(t, how, 16), 16).first() for how in ("subject", "object", "random")}
    assert len({r["total"] for r in rows.values()}) == 1
    assert rows["object"]["sd"] > rows["subject"]["sd"] and rows["random"]["sd"] < rows["object"]["sd"]


def test_dictionary(spark):
    t = spark.createDataFrame(CAMPUS, "s string, p string, o string")
    names = build_dictionary(t)
    assert names.count() == names.select("id").distinct().count() == 9
    assert sorted(r["id"] for r in dense_dictionary(t).collect()) == list(range(9))
    assert encode(t).join(names, F.col("s") == F.col("id")).count() == len(CAMPUS)


def test_operators(spark):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "k int, v string")
    assert A.minus(df, spark.createDataFrame([(1,)], "z int")).count() == 2
    assert A.minus(df, spark.createDataFrame([(1,)], "k int")).count() == 1
    chain = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a")], "s string, o string")
    assert A.path_closure(chain).count() == 9
    assert A.path_closure(chain.where("s != 'c'"), reflexive=True).count() == 6


def test_a_live_answer_outlives_its_modules(spark, sf):
    """An answer that is held can still be run after its modules were evicted; then their files go."""
    import gc

    store, bgp = store_of(spark, sf), template("uni_q02")
    engine = Engine(store, threshold=1, budget=50.0)
    engine.run(bgp)
    live = engine.run(bgp)
    assert engine.log[-1].mode == "parallel"
    tables = [m.table for m in engine.index.modules.values() if m.table]
    engine.budget = 0.0
    engine.run(template("enc_y2"))  # its modules evict all that there are
    assert engine.index.replicas == 0 and engine.index.retired and engine.mode(bgp)[0] == "distributed"
    assert same(live, plain_of(store, bgp))
    derived = live.select("x").distinct()
    assert derived.count() > 0
    del live, derived
    gc.collect()
    engine.index.sweep()
    assert not engine.index.retired and not any(spark.catalog.tableExists(t) for t in tables)


def test_redistribution_is_counted(spark, sf):
    engine = Engine(store_of(spark, sf), threshold=2, budget=50.0)
    for _ in range(3):
        engine.run(template("uni_q02"))
    assert engine.log[0].sent == 0 and engine.log[1].sent > 0 and engine.log[2].sent == 0
    assert engine.index.sent == sum(m.sent for m in engine.index.modules.values())


def leaves(df):
    found = df._jdf.queryExecution().withCachedData().collectLeaves()
    return [found.apply(k).getClass().getSimpleName() for k in range(found.size())]


@pytest.mark.parametrize("name", ["uni_q02", "enc_y2", "div_c1"])
def test_steps_are_not_computed_again(spark, sf, name):
    """A semi-join reads its left side twice; what is behind it is kept, so work is linear in the patterns."""
    store, bgp = store_of(spark, sf), template(name)
    out = distributed(store, bgp)
    assert len(leaves(out)) <= 2 * len(bgp) and leaves(out).count("LogicalRelation") <= len(bgp)
    assert same(out.drop("home"), plain_of(store, bgp))


def test_keys_are_sent_once_for_several_patterns(spark, sf):
    store, bgp = store_of(spark, sf), template("uni_q02")
    once, each = Traffic(), Traffic()
    a, b = distributed(store, bgp, Options(), once), distributed(store, bgp, Options(fuse=False), each)
    assert same(a, b) and len(once.steps) < len(each.steps) and once.total <= each.total


def test_each_worker_has_its_own_order(spark, sf):
    from trellis.adapt.redistribute import parallel_by_worker
    from trellis.operators.evaluate import star_by_worker

    rows = [(f"s{k}", p, f"{p}{j}") for k in range(200) for p, n in (("a", 1 + k % 5), ("b", 1 + k % 3), ("c", 1)) for j in range(n)]
    store = build(spark, spark.createDataFrame(rows, "s string, p string, o string"), 4)
    local = store.local_statistics()
    assert sum(v["a"].card for v in local.values()) == store.stats["a"].card and sum(v["a"].n_s for v in local.values()) == 200
    bgp = BGP.parse("?x a ?y . ?x b ?z . ?x c ?w")
    out = star_by_worker(store, bgp)
    assert exchanges(out) == 0 and same(out.drop("home"), plain_of(store, bgp))
    store, bgp = store_of(spark, sf), template("uni_q02")
    engine = Engine(store, threshold=1, budget=50.0).train([bgp])
    out = parallel_by_worker(engine.index, engine.tree(bgp))
    assert exchanges(out) == 0 and same(out.drop("home"), plain_of(store, bgp))


def test_rare_predicates_share_folders(spark):
    rows = [(f"s{k % 40}", f"p{k % 30}", f"o{k % 7}") for k in range(600)] + [("s1", "often", f"o{k}") for k in range(50)]
    triples = spark.createDataFrame(rows, "s string, p string, o string").distinct()
    whole, few = build(spark, triples, 3), build(spark, triples, 3, folders=2)
    count = lambda store: spark.table(store.ps).select("folder").distinct().count()
    assert whole.frequent is None and count(whole) == 31 and len(few.frequent) == 2 and "often" in few.frequent and count(few) < 31
    for p in ("often", "p3", "p29"):
        bgp = BGP.parse(f"?x {p} ?y . ?x p4 ?z")
        assert same(distributed(few, bgp).drop("home"), plain_of(whole, bgp))
        scan = few.scan(Pattern(Var("s"), BGP.parse(f"?x {p} ?y").patterns[0].p, Var("o")))
        assert "PartitionFilters: [isnotnull(folder" in scan._jdf.queryExecution().executedPlan().toString()
    assert whole.raw_stats == few.raw_stats


def test_other_index_orders(spark, sf):
    from trellis.plans.patterns import Const

    store = store_of(spark, sf)
    for order in ("osp", "pos"):
        store.add_order(order)
    p = Pattern(Var("s"), Var("p"), Const("nation/1"))
    out = store.look_up(p)
    assert "_osp_" in out._jdf.queryExecution().executedPlan().toString() and "SelectedBucketsCount: 1 out of" in out._jdf.queryExecution().executedPlan().toString()
    assert same(out, spark.table(store.ps).select("s", "p", "o").where("o = 'nation/1'"))
    with pytest.raises(ValueError):
        store.add_order("sps")


def test_recovery_from_a_stored_log(spark, sf, tmp_path):
    store, path = store_of(spark, sf), str(tmp_path / "log")
    engine = Engine(store, threshold=3, budget=50.0)
    for name in ("uni_q11", "uni_q11"):
        engine.run(template(name))
    engine.save(path)
    engine.run(template("uni_q11"))
    engine.run("SELECT ?x WHERE { ?x locatedIn nation/1 }")
    engine.save(path)
    engine.save(path)
    again = engine.restore(path)
    counts = lambda e: {p: (n.count, dict(n.constants)) for p, n in e.heat.walk()}
    assert counts(again) == counts(engine) and set(again.index.modules) == set(engine.index.modules)
    assert again.mode(template("uni_q11"))[0] == "parallel"


def test_a_monitored_stream_heats_the_same_paths(spark, sf, tmp_path):
    """The trees of a stream are the engine's own, and a batch that comes again counts once."""
    from trellis.plans.patterns import query_text
    from trellis.streaming.streams import heat_batch, monitor

    store = store_of(spark, sf)
    names = ["uni_q02", "uni_q02", "enc_y2", "div_f1", "uni_q11", "lif_b2"]
    log = spark.createDataFrame([(k, query_text(template(x))) for k, x in enumerate(names)], "qid long, text string").withColumn("ts", F.timestamp_seconds(F.col("qid")))
    log.write.parquet(str(tmp_path / "log"))
    stream = spark.readStream.schema("qid long, text string, ts timestamp").parquet(str(tmp_path / "log"))
    own, watched = Engine(store, threshold=100), Engine(store, threshold=100)
    for x in names:
        own.heat.add(own.tree(template(x)))
    counts = lambda e: {p: (n.count, dict(n.constants)) for p, n in e.heat.walk()}
    monitor(stream, watched, checkpoint=str(tmp_path / "a"))
    assert counts(watched) == counts(own)
    monitor(stream, watched, checkpoint=str(tmp_path / "b"))  # the same batch under the same name
    assert counts(watched) == counts(own)
    assert {r["path"] for r in heat_batch(log, own)} == {"/".join(f"{'>' if out else '<'}{p}" for p, out in path) for path, _ in own.heat.walk()}


def test_generator():
    from trellis.plans.patterns import components, query_text
    from trellis.workloads import POOL, Slots, structures, uni_pool, uni_workload

    slots = Slots(customers=1500, suppliers=100, parts=2000)
    by = {}
    for name, bgp in uni_pool(slots):
        by.setdefault(name, []).append(query_text(bgp))
    assert len(by["uni_q02"]) == POOL["uni_q02"] == 18 and len(by["uni_q09"]) == 30 and len(by["uni_q06"]) == len(by["uni_q14"]) == 1
    assert len(by["uni_q03"]) == 1000 and all(len(v) == len(set(v)) for v in by.values())
    assert max(int(x.split("customer/")[1].split()[0]) for x in by["uni_q03"]) > 1000
    shapes = structures(template("uni_q02"))
    assert all(len(b) >= 2 and len(components(b)) == 1 for b in shapes)
    twins = [b for b in shapes if len(b) == 6]
    assert len(twins) == 4  # two of its three classes have a twin
    assert [query_text(b) for _, b in uni_workload(20, slots=slots)] == [query_text(b) for _, b in uni_workload(20, slots=slots)]


def test_unconnected_patterns_are_refused(spark, sf):
    from trellis import baselines

    store, bgp = store_of(spark, sf), BGP.parse("?a locatedIn ?b . ?c partOf ?d")
    for kind in ("batch_random", "merge", "explore", "central"):
        with pytest.raises(ValueError):
            baselines.answer(store, kind, bgp)


ORACLES = ["uni_q01", "uni_q02", "uni_q07", "uni_l3", "div_l4", "div_s7", "div_f1", "div_c1", "enc_y2", "lif_b1", "statistics", "op_join_asof", "op_path_closure", "op_udaf_majority", "baseline_khop", "baseline_summary", "baseline_min_cut", "baseline_khop_undirected", "st_session", "st_late_stream", "op_agg_approx", "op_sample", "op_fn_hash", "op_udtf_edges", "placement_invariants", "index_orders", "literal_core_uni_q02"]


@pytest.mark.parametrize("name", ORACLES)
def test_against_sql(spark, sf, name):
    import duckdb

    from trellis.queries import ORACLE_SQL, QUERIES
    from trellis.sources.vocab import TABLES

    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    want = con.sql(ORACLE_SQL[name])
    got = QUERIES[name](spark, sf)
    assert sorted(got.columns) == sorted(want.columns)
    order = sorted(got.columns)
    text = lambda rows: sorted(tuple("-" if v is None else f"{v:.4f}" if isinstance(v, float) else str(v) for v in r) for r in rows)
    assert text(map(tuple, got.select(*order).collect())) == text(want.project(", ".join(f'"{c}"' for c in order)).fetchall())


def test_played_queries_are_executed(spark, sf):
    from trellis import measures
    from trellis.workloads import TEMPLATES

    engine = Engine(store_of(spark, sf, 8), adaptive=False)
    name = next(x for x in TEMPLATES if engine.mode(template(x))[0] == "star")
    measures._played(engine, [(name, template(name))])  # what only planning needs is known now
    spark.sparkContext.setJobGroup("played", "a star's answer")
    try:
        rows = measures._played(engine, [(name, template(name))])
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert rows[0][2] == "star" and rows[0][4] == 0
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("played")) > 0


def test_placed_on_demand(spark, sf):
    """A query has placed what its patterns can match and no more; all of it is there for who reads a whole copy."""
    from trellis.sources.store import TableStore
    from trellis.sources.vocab import CORE, triples_from_tables

    store = TableStore(spark, sf, 4, CORE)
    bgp = BGP.parse("?x type class/Customer . ?x locatedIn ?n . ?n partOf region/1")
    got = distributed(store, bgp)
    assert store.placed == {"ps": {"locatedIn"}, "po": {"type~customer", "partOf"}}
    assert same(got.drop("home"), plain_of(store, bgp))
    whole = triples_from_tables(spark, sf, CORE).select("s", "p", "o")
    assert same(spark.table(store.ps).select("s", "p", "o"), whole)
    placed = spark.table(store.ps)
    assert same(vertex_degree(placed, 4).drop("home"), vertex_degree(placed.select("s", "p", "o")))
    assert distributed(store, BGP.parse("?x nowhere ?y")).count() == 0


def test_table_function_reads_a_table(spark, sf):
    from trellis.queries import QUERIES

    assert any("customer.parquet" in f for f in QUERIES["op_udtf_edges"](spark, sf).inputFiles())


def test_replicas_on_demand(spark, sf):
    """What a query has replicated is what two hops over the whole graph give of the mappings that it can match."""
    import duckdb

    from trellis import baselines
    from trellis.sources.store import TableStore
    from trellis.sources.vocab import CORE, TABLES, triples_sql

    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    triples = con.sql(triples_sql(CORE)).fetchall()
    triples = [t for t in triples if None not in t]
    names = {s for s, _, _ in triples}
    ends = spark.createDataFrame([(s, s.split("/")[0]) for s in names], "s string, head string").select("s", home("s", 4), home("head", 4)).collect()
    by_s, by_o = {}, {}
    for t in triples:
        by_s.setdefault(t[0], []).append(t)
        by_o.setdefault(t[2], []).append(t)
    for kind, name in (("khop", "uni_q08"), ("khop_prefix", "uni_q08"), ("khop_undirected", "uni_q11")):
        at = {r[0]: r[2 if kind == "khop_prefix" else 1] for r in ends}
        want = {(at[t[0]], *t) for t in triples}
        through = {(h, s, p, o) for h, s, p, o in want if p != "type"}
        want |= {(h, *t) for h, o in {(x[0], x[3]) for x in through} for t in by_s.get(o, ())}
        if kind == "khop_undirected":
            want |= {(h, *t) for h, s in {x[:2] for x in through} for t in by_o.get(s, ()) if t[1] != "type"}
        store, bgp = TableStore(spark, sf, 4, CORE), template(name)
        asked, classes = {str(p.p) for p in bgp}, {str(p.o) for p in bgp if str(p.p) == "type"}
        want = sorted(x for x in want if x[2] in asked and (x[2] != "type" or x[3] in classes))
        assert sorted(tuple(r) for r in baselines.khop_replicas(store, kind, bgp).select("home", "s", "p", "o").collect()) == want
        assert store.placed == {"ps": set(), "po": set()}


def test_partitioning_in_portions_gives_the_same_parts(spark, monkeypatch):
    """Every vertex has one part, however many portions the voters are counted in."""
    from trellis import baselines

    rows = [(f"a/{k}", "p", f"a/{k * 7 % 20}") for k in range(20)] + [(f"b/{k}", "p", f"b/{k * 3 % 20 + 1}") for k in range(20)]
    triples = spark.createDataFrame(rows, "s string, p string, o string")
    once = {r["v"]: r["part"] for r in baselines.min_cut(triples, 2, rounds=1).collect()}
    monkeypatch.setattr(baselines, "VOTES", 30)
    assert {r["v"]: r["part"] for r in baselines.min_cut(triples, 2, rounds=1).collect()} == once
    names = {x for s, _, o in rows if s != o for x in (s, o)}
    assert len(once) == len(names) and set(once.values()) <= {0, 1}


def test_partitioning_reads_names_once(spark, sf, monkeypatch):
    """Names are read and hashed once, whatever the number of rounds; the parts are what plain counting of votes gives."""
    import math
    from collections import Counter, defaultdict

    from pyspark.sql import functions as F

    from trellis import baselines

    rows = [(f"a/{k}", "p", f"a/{k * 7 % 20}") for k in range(20)] + [(f"b/{k}", "p", f"a/{k * 3 % 20 + 1}") for k in range(20)] + [("a/3", "p", "b/4")] * 3
    triples = spark.createDataFrame(rows, "s string, p string, o string")
    near = defaultdict(list)
    names = sorted({x for s, _, o in rows if s != o for x in (s, o)})
    of = {r["x"]: r for r in spark.createDataFrame([(x,) for x in names], "x string").select("x", F.xxhash64("x").alias("v")).select("x", "v", F.pmod(F.xxhash64(F.lit(1), "v"), F.lit(3)).cast("int").alias("part"), *[(F.pmod(F.xxhash64(F.lit(r), "v"), F.lit(1_000_000)) / 1_000_000).alias(f"luck{r}") for r in range(2)]).collect()}
    tie = {(r["k"], r["r"]): r["x"] for r in spark.range(3).selectExpr("cast(id as int) as k", "explode(array(0, 1)) as r").select("k", "r", F.xxhash64("k", "r").alias("x")).collect()}
    for s, _, o in rows:
        if s != o:
            near[s].append(o)
            near[o].append(s)
    part = {x: of[x]["part"] for x in names}
    cap = math.ceil(1.1 * len(names) / 3)
    for r in range(2):
        wish = {x: max(Counter(part[y] for y in near[x]).items(), key=lambda kn: (kn[1], tie[kn[0], r]))[0] for x in names}
        sizes, asking = Counter(part.values()), Counter(wish[x] for x in names if wish[x] != part[x])
        room = {k: max(0.0, min(1.0, (cap - sizes[k]) / max(asking[k], 1))) for k in range(3)}
        part = {x: wish[x] if wish[x] != part[x] and of[x][f"luck{r}"] < room[wish[x]] else part[x] for x in names}
    got = {r["v"]: r["part"] for r in baselines.min_cut(triples, 3, rounds=2).collect()}
    assert got == {of[x]["v"]: part[x] for x in names}

    # the tables are read for the number of their rows and for their names, and not again in a round
    read = []
    for_real = baselines._Bucketed.add
    monkeypatch.setattr(baselines._Bucketed, "add", lambda self, rows, *order: (read.append([f for f in rows.inputFiles() if sf in f]), for_real(self, rows, *order))[1])
    store = store_of(spark, sf)
    stars = baselines.graph_of(store)
    assert sum(len(x.objects) for x in stars) == len(store.units)
    assert baselines.min_cut(stars, 4, rounds=2).count() > 0
    assert sum(map(bool, read)) < len(stars) and not any(read[-4:])


@pytest.mark.parametrize("odd", [False, True])
def test_statistics_are_counted_from_the_tables(spark, sf, tmp_path, odd):
    """The whole graph's statistics are those of its placed triples, and place nothing; also of lines that repeat, and of labels that read like names."""
    from pyspark.sql import functions as F

    from trellis.plans.stats import collect_statistics, predicate_statistics
    from trellis.sources.store import TableStore
    from trellis.sources.vocab import CORE, TABLES, triples_from_tables

    if odd:
        for t in TABLES:
            rows = spark.read.parquet(f"{sf}/{t}.parquet")
            if t == "lineitem":
                few = rows.orderBy(*rows.columns).limit(50)
                rows = rows.union(few).union(few.withColumn("l_quantity", (F.col("l_quantity") + 1).cast(rows.schema["l_quantity"].dataType))).union(few.withColumn("l_returnflag", F.lit(None).cast("string")))
            if t == "part":
                line = spark.read.parquet(f"{sf}/lineitem.parquet").selectExpr("concat('line/', l_orderkey, '-', l_linenumber, '-', l_partkey, '-', l_suppkey) as name").orderBy("name").first()["name"]
                rows = rows.withColumn("p_name", F.when(F.col("p_partkey") < 3, F.lit(line)).when(F.col("p_partkey") < 6, F.lit("event/1")).otherwise(F.col("p_name")))
            rows.write.parquet(f"{tmp_path}/{t}.parquet")
        sf = str(tmp_path)
    store = TableStore(spark, sf, 4, CORE)
    want = collect_statistics(predicate_statistics(triples_from_tables(spark, sf, CORE).select("s", "p", "o")))
    assert store.raw_stats == want
    assert store.total == sum(p.card for p in want.values()) and store.placed == {"ps": set(), "po": set()}
