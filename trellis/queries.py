"""Registered queries of the engine, and their oracles as SQL over the relational tables."""

from __future__ import annotations

from collections.abc import Callable
from copy import copy
from functools import partial, reduce
from itertools import permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, measures
from .adapt.engine import Engine
from .adapt.redistribute import parallel_by_worker
from .operators import algebra_queries
from .operators.evaluate import Options, distributed, execute, plain_of, projected, star_by_worker
from .plans.cost import plan_order
from .plans.stats import predicate_statistics, profile, vertex_degree
from .sources.files import round_trip_csv, round_trip_json, round_trip_ntriples
from .sources.store import balance, place_by, store_of
from .sources.vocab import CORE, triples_from_tables, triples_sql
from .streaming import queries as streaming_queries
from .workloads import HEAVY, TEMPLATES, query_text, sql_of, template

Query = Callable[[SparkSession, str], DataFrame]
WORKERS = 8


def answer(name: str, spark: SparkSession, sf_dir: str, mode: str = "distributed") -> DataFrame:
    """A template's answers by one way of evaluation; of many answers, their number and ends."""
    store, bgp = store_of(spark, sf_dir, WORKERS), template(name)
    if mode == "parallel":
        engine = Engine(store, threshold=1, budget=50.0).train([bgp])
        out = engine.answer(bgp)[0]
    elif mode == "auto":
        out = Engine(store, adaptive=False).answer(bgp)[0]
    elif mode == "plain":
        out = plain_of(store, bgp)
    else:
        out = distributed(store, bgp, Options(**MODES[mode]))
    return summed(out.drop("home"), name)


#: Ways to use the placement: both properties, one, or none.
MODES = {"distributed": {}, "no_pinning": {"pinning": False}, "no_locality": {"locality": False, "pinning": False}}


def summed(out: DataFrame, name: str) -> DataFrame:
    names = template(name).variables
    if name not in HEAVY:
        return projected(out, names)
    v = names[0]
    return out.agg(F.count("*").alias("n"), F.count_distinct(v).alias("n_first"), F.min(v).alias("least"), F.max(v).alias("greatest"))


def summed_sql(name: str) -> str:
    sql, v = sql_of(template(name)), template(name).variables[0]
    return f"select count(*) as n, count(distinct {v}) as n_first, min({v}) as least, max({v}) as greatest from ({sql}) as q" if name in HEAVY else sql


def baseline(kind: str, name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """A template by a comparison system over the whole graph."""
    return summed(baselines.answer(store_of(spark, sf_dir, WORKERS), kind, template(name)), name)


BASELINES = {"batch_random": "uni_q02", "batch_range": "uni_q02", "khop": "uni_q08", "khop_undirected": "uni_q11", "khop_prefix": "uni_q08", "min_cut": "uni_q12", "summary": "uni_q11", "merge": "uni_q02", "explore": "uni_q02", "central": "uni_q11", "broadcast_all": "uni_q02"}


def triples_by_predicate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return triples_from_tables(spark, sf_dir).groupBy("p").agg(F.count("*").alias("triples"))


def statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = predicate_statistics(spark.table(store_of(spark, sf_dir, WORKERS).ps), workers=WORKERS)
    return s.select("p", "card", "n_s", "n_o", *[F.round(c, 4).alias(c) for c in ("score_s", "score_o", "p_ps", "p_po")])


def degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = vertex_degree(spark.table(store_of(spark, sf_dir, WORKERS).ps), workers=WORKERS)
    return d.groupBy("degree").agg(F.count("*").alias("vertices"), F.sum("deg_in").alias("deg_in"), F.sum("deg_out").alias("deg_out"))


def data_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = profile(spark.table(store_of(spark, sf_dir, WORKERS).ps), workers=WORKERS)
    return p.select("triples", "subjects", "objects", "both", "predicates", *[F.round(c, 4).alias(c) for c in ("in_avg", "in_sd", "out_avg", "out_sd")])


def placement(how: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    triples = triples_from_tables(spark, sf_dir, CORE).select("s", "p", "o")
    return balance(place_by(triples, how, 16), 16).withColumn("placement", F.lit(how))


def placement_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What every placement keeps: all triples once, their mean, and how its extremes lie around it."""
    parts = [placement(how, spark, sf_dir).select("placement", "total", "avg", ((F.col("max") >= F.col("avg")) & (F.col("min") <= F.col("avg")) & (F.col("sd") <= F.col("max") - F.col("min"))).alias("ordered")) for how in ("subject", "object", "random")]
    return parts[0].union(parts[1]).union(parts[2])


def index_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Look-ups of three patterns by each of the six orders of s, p and o, and by the one that suits best."""
    from .plans.patterns import Const, Pattern, Var

    store = store_of(spark, sf_dir, WORKERS)
    s, p, o = Var("s"), Var("p"), Var("o")
    wanted = {"subject": Pattern(Const("nation/1"), p, o), "object": Pattern(s, p, Const("nation/1")), "predicate and object": Pattern(s, Const("partOf"), Const("region/1"))}
    rows = []
    for order in (*map("".join, permutations("spo")), "best"):
        if order != "best":
            store.add_order(order)
        one = store if order == "best" else copy(store)
        one.copies = store.copies if order == "best" else {order: store.copies[order]}
        rows += [one.look_up(q).agg(F.count("*").alias("n")).select(F.lit(order).alias("index_order"), F.lit(name).alias("pattern"), "n") for name, q in wanted.items()]
    return reduce(DataFrame.union, rows)


def by_worker(name: str, kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """A template answered with each worker's own order, from its own statistics."""
    store, bgp = store_of(spark, sf_dir, WORKERS), template(name)
    if kind == "star":
        return summed(star_by_worker(store, bgp).drop("home"), name)
    engine = Engine(store, threshold=1, budget=50.0).train([bgp])
    return summed(parallel_by_worker(engine.index, engine.tree(bgp)).drop("home"), name)


def literal_core(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """A template from the index, with the core as the scores alone have it, however few values it takes."""
    engine = Engine(store_of(spark, sf_dir, WORKERS), threshold=1, budget=50.0, guard=False).train([template(name)])
    return summed(engine.answer(template(name))[0].drop("home"), name)


def placement_modulo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The simplification on numbers: an order's key modulo the workers; counts by worker index."""
    from .sources.store import seeds

    numbers = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_orderkey").alias("s"), F.lit("placedBy").alias("p"), F.col("o_custkey").alias("o"))
    index = F.array_position(F.array(*map(F.lit, seeds(16))), F.col("home")) - 1
    return place_by(numbers, "modulo", 16).groupBy(index.alias("worker")).agg(F.count("*").alias("n"))


def encoded_answer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A query over the store of numbers, decoded at the end."""
    store = store_of(spark, sf_dir, WORKERS, encoded=True)
    bgp = template("div_s5")
    return projected(store.decode(distributed(store, bgp)).drop("home"), bgp.variables)


def plan_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order, cases and costs that the planner gives to every template."""
    store, rows = store_of(spark, sf_dir, WORKERS), []
    for name in TEMPLATES:
        bgp = template(name)
        store.refine_all(bgp)
        plan = plan_order(bgp, store.knowledge, WORKERS)
        rows += [(name, k, str(p), c.value if c else "scan", v, float(plan.state.cost)) for k, (p, c, v) in enumerate(plan.steps)]
    return spark.createDataFrame(rows, "query string, step int, pattern string, join_case string, column_joined string, cost double")


def dictionary_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sources.dictionary import build_dictionary, decode, encode

    triples = triples_from_tables(spark, sf_dir, ("locatedIn", "basedIn", "partOf")).select("s", "p", "o")
    names = build_dictionary(triples)
    back = decode(encode(triples), names, ["s", "o"])
    return back.groupBy("p").agg(F.count("*").alias("triples"), F.count_distinct("s").alias("subjects"), F.count_distinct("o").alias("objects"))


def text_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text with OPTIONAL, FILTER, ORDER BY and LIMIT through the engine."""
    text = 'SELECT ?d ?q WHERE { ?d lang lang/de . OPTIONAL { ?d quality ?q } FILTER(length(?d) > 5) } ORDER BY ?d LIMIT 20'
    return Engine(store_of(spark, sf_dir, WORKERS), adaptive=False).run(text)


def variable_predicate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .plans.patterns import BGP

    return distributed(store_of(spark, sf_dir, WORKERS), BGP.of(("nation/1", "?p", "?o"))).select("p", "o")


def ask(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Engine(store_of(spark, sf_dir, WORKERS), adaptive=False).run("ASK { ?x locatedIn nation/1 . ?x segment segment/BUILDING }")


def construct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples made of a pattern's answers: customers and suppliers of one nation that deal with each other."""
    out = distributed(store_of(spark, sf_dir, WORKERS), template("uni_q02"))
    return out.select(F.col("x").alias("s"), F.lit("dealsNear").alias("p"), F.col("z").alias("o"))


def pinned_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A fixed order executed as given: the triangle from the supplier's side."""
    from .plans.patterns import BGP

    store = store_of(spark, sf_dir, WORKERS)
    bgp = BGP.parse("?z basedIn ?y . ?x boughtFrom ?z . ?x locatedIn ?y")
    return projected(execute(store, plan_order(bgp, store.knowledge, WORKERS, seed="none")).drop("home"), ("x", "y", "z"))


def _registry() -> tuple[dict[str, Query], dict[str, str]]:
    q: dict[str, Query] = {}
    sql: dict[str, str] = {}
    for name in TEMPLATES:
        q[name] = partial(answer, name)
        sql[name] = summed_sql(name)
    for name in ("uni_q02", "uni_q08", "uni_q11", "uni_q07", "div_l1", "div_l2", "div_f1", "div_f2", "div_c2", "enc_y1", "enc_y2", "lif_b2"):
        q[f"parallel_{name}"] = partial(answer, name, mode="parallel")
        sql[f"parallel_{name}"] = summed_sql(name)
    for name in ("uni_q02", "uni_q11", "enc_y4"):
        for mode in ("no_pinning", "no_locality", "plain"):
            q[f"{mode}_{name}"] = partial(answer, name, mode=mode)
            sql[f"{mode}_{name}"] = summed_sql(name)
    for name, kind in (("uni_q04", "star"), ("uni_q02", "parallel"), ("div_f1", "parallel")):
        q[f"by_worker_{name}"] = partial(by_worker, name, kind)
        sql[f"by_worker_{name}"] = summed_sql(name)
    for name in ("uni_q02", "uni_q11", "enc_y4"):
        q[f"literal_core_{name}"] = partial(literal_core, name)
        sql[f"literal_core_{name}"] = summed_sql(name)
    for name in ("uni_q04", "div_s2"):
        q[f"star_{name}"] = partial(answer, name, mode="auto")
        sql[f"star_{name}"] = summed_sql(name)
    for kind, name in BASELINES.items():
        q[f"baseline_{kind}"] = partial(baseline, kind, name)
        sql[f"baseline_{kind}"] = summed_sql(name)
    core = triples_sql(CORE)
    q["triples_by_predicate"] = triples_by_predicate
    sql["triples_by_predicate"] = f"select p, count(*) as triples from ({triples_sql()}) as t where s is not null and o is not null group by p"
    ends = f"(with t as ({core}), e as (select s as v, 0 as inward from t union all select o, 1 from t) select v, sum(inward) as deg_in, sum(1 - inward) as deg_out, count(*) as degree from e group by v)"
    q["statistics"] = statistics
    sql["statistics"] = (
        f"with t as materialized ({core}), d as materialized (select v, count(*) as degree from (select s as v from t union all select o from t) as e group by v), "
        "ss as (select p, sum(k) as card, count(*) as n_s, avg(degree) as score_s from (select p, s as v, count(*) as k from t group by p, s) as a join d using (v) group by p), "
        "oo as (select p, count(*) as n_o, avg(degree) as score_o from (select distinct p, o as v from t) as a join d using (v) group by p) "
        "select p, cast(card as bigint) as card, n_s, n_o, round(score_s, 4) as score_s, round(score_o, 4) as score_o, round(card / n_s, 4) as p_ps, round(card / n_o, 4) as p_po from ss join oo using (p)"
    )
    q["degrees"] = degrees
    sql["degrees"] = f"select degree, count(*) as vertices, cast(sum(deg_in) as bigint) as deg_in, cast(sum(deg_out) as bigint) as deg_out from {ends} as d group by degree"
    q["data_profile"] = data_profile
    sql["data_profile"] = (
        f"with d as materialized (select * from {ends} as x) select cast(sum(deg_out) as bigint) as triples, count(*) filter (deg_out > 0) as subjects, count(*) filter (deg_in > 0) as objects, "
        f'count(*) filter (deg_in > 0 and deg_out > 0) as "both", {len(CORE)} :: bigint as predicates, round(avg(deg_in) filter (deg_in > 0), 4) as in_avg, round(stddev_pop(deg_in) filter (deg_in > 0), 4) as in_sd, '
        "round(avg(deg_out) filter (deg_out > 0), 4) as out_avg, round(stddev_pop(deg_out) filter (deg_out > 0), 4) as out_sd from d"
    )
    for how in ("subject", "object", "random"):
        q[f"placement_{how}"] = partial(placement, how)
    q["placement_invariants"] = placement_invariants
    sql["placement_invariants"] = f"select h.placement, n as total, n / 16 as avg, true as ordered from (select count(*) as n from ({core}) as t) as c, (values ('subject'), ('object'), ('random')) as h(placement)"
    q["index_orders"] = index_orders
    sql["index_orders"] = f"with t as materialized ({core}) select i.index_order, x.pattern, x.n from (values ('spo'), ('sop'), ('pso'), ('pos'), ('osp'), ('ops'), ('best')) as i(index_order), (select 'subject' as pattern, count(*) filter (s = 'nation/1') as n from t union all select 'object', count(*) filter (o = 'nation/1') from t union all select 'predicate and object', count(*) filter (p = 'partOf' and o = 'region/1') from t) as x"
    q["placement_modulo"] = placement_modulo
    sql["placement_modulo"] = "select cast(o_orderkey % 16 as bigint) as worker, count(*) as n from orders group by 1"
    q["encoded_div_s5"] = encoded_answer
    sql["encoded_div_s5"] = summed_sql("div_s5")
    q["plans"] = plan_rows
    q["dictionary"] = dictionary_terms
    sql["dictionary"] = f"select p, count(*) as triples, count(distinct s) as subjects, count(distinct o) as objects from ({triples_sql(('locatedIn', 'basedIn', 'partOf'))}) as t group by p"
    q["text_query"] = text_query
    sql["text_query"] = "select x.d as d, case when l.quality is null then null else concat('quality/', l.quality) end as q from (select doc_id, concat('doc/', doc_id) as d from documents where lang = 'de') as x left join labels l on l.doc_id = x.doc_id where length(x.d) > 5 order by x.d limit 20"
    q["variable_predicate"] = variable_predicate
    sql["variable_predicate"] = f"select p, o from ({core}) as t where s = 'nation/1'"
    q["ask"] = ask
    sql["ask"] = "select count(*) > 0 as answer from customer where c_nationkey = 1 and c_mktsegment = 'BUILDING'"
    q["construct"] = construct
    sql["construct"] = f"select x as s, 'dealsNear' as p, z as o from ({sql_of(template('uni_q02'))}) as q"
    q["pinned_plan"] = pinned_plan
    sql["pinned_plan"] = f"select x, y, z from ({sql_of(template('uni_q02'))}) as q"
    q["ntriples"], sql["ntriples"] = round_trip_ntriples, f"select p, count(*) as triples from ({triples_sql(('label', 'partOf', 'locatedIn'))}) as t group by p"
    q["edges_csv"], sql["edges_csv"] = round_trip_csv, "select o_orderstatus as status, count(*) as n from orders group by 1"
    q["edges_json"], sql["edges_json"] = round_trip_json, "select o_orderpriority as priority, count(*) as n from orders group by 1"
    q |= measures.QUERIES
    sql |= measures.ORACLE_SQL
    q |= algebra_queries.QUERIES
    sql |= algebra_queries.ORACLE_SQL
    q |= streaming_queries.QUERIES
    sql |= streaming_queries.ORACLE_SQL
    return q, sql


QUERIES, ORACLE_SQL = _registry()
TEXTS = {name: query_text(template(name)) for name in TEMPLATES}
