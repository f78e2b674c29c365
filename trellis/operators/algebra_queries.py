"""Registered uses of the operators around the methods, with their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.udfs import iri_kind, majority_vote, register
from ..sources.vocab import triples_from_tables, triples_sql, typed_object
from . import algebra as A

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def op(sql: str | None):
    """Registers a function under its name, with its oracle."""

    def add(f: Query) -> Query:
        QUERIES[f"op_{f.__name__}"] = f
        if sql:
            ORACLE_SQL[f"op_{f.__name__}"] = sql
        return f

    return add


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@op("select l_orderkey, l_quantity from lineitem where l_shipdate >= timestamp '1998-01-01' and l_quantity > 45")
def scan_parquet(s, d):
    return t(s, d, "lineitem").where("l_shipdate >= timestamp '1998-01-01' and l_quantity > 45").select("l_orderkey", "l_quantity")


@op("select distinct c_mktsegment from customer")
def project_distinct(s, d):
    return t(s, d, "customer").select("c_mktsegment").distinct()


@op("select p_partkey, p_retailprice from part where p_retailprice > 1500 and p_size <> 10 and p_size <= 30")
def filter_cmp(s, d):
    return t(s, d, "part").where((F.col("p_retailprice") > 1500) & (F.col("p_size") != 10) & (F.col("p_size") <= 30)).select("p_partkey", "p_retailprice")


@op("select p_partkey from part where p_brand in ('Brand#1', 'Brand#2') and p_size between 5 and 20 and p_name is not null")
def filter_in_between(s, d):
    return t(s, d, "part").where(F.col("p_brand").isin("Brand#1", "Brand#2") & F.col("p_size").between(5, 20) & F.col("p_name").isNotNull()).select("p_partkey")


@op("select p_partkey, p_name from part where regexp_matches(p_name, '^[a-m]') and p_name like '%e%'")
def filter_regex_like(s, d):
    return t(s, d, "part").where(F.col("p_name").rlike("^[a-m]") & F.col("p_name").like("%e%")).select("p_partkey", "p_name")


@op("select o_orderkey, case when o_totalprice > 200000 then 'high' else 'low' end as band, coalesce(nullif(o_orderstatus, 'P'), 'pending') as state from orders")
def bind_if_coalesce(s, d):
    return t(s, d, "orders").select("o_orderkey", F.when(F.col("o_totalprice") > 200000, "high").otherwise("low").alias("band"), F.coalesce(F.nullif(F.col("o_orderstatus"), F.lit("P")), F.lit("pending")).alias("state"))


@op("select n_name, v.tag from nation join (values (1, 'one'), (2, 'two')) as v(k, tag) on n_nationkey = v.k")
def values_inline(s, d):
    inline = s.sql("select * from values (1, 'one'), (2, 'two') as v(n_nationkey, tag)")
    return t(s, d, "nation").join(inline, "n_nationkey").select("n_name", "tag")


_INNER = "select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1"


def _inner(s, d, strategy):
    left = t(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return A.join(left, t(s, d, "customer").select("c_custkey", "c_mktsegment"), ["c_custkey"], strategy).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


for _strategy in ("auto", "broadcast", "shuffle_hash", "merge"):
    QUERIES[f"op_join_inner_{_strategy}"] = lambda s, d, k=_strategy: _inner(s, d, k)
    ORACLE_SQL[f"op_join_inner_{_strategy}"] = _INNER


@op("select d.doc_id, quality from documents d left join labels l on l.doc_id = d.doc_id")
def join_optional(s, d):
    return t(s, d, "documents").select("doc_id").join(t(s, d, "labels").select("doc_id", "quality"), "doc_id", "left")


@op("select c_custkey, count(event_id) as events from customer full join events on c_custkey = user_id group by 1")
def join_full(s, d):
    return t(s, d, "customer").join(t(s, d, "events"), F.col("c_custkey") == F.col("user_id"), "full").groupBy("c_custkey").agg(F.count("event_id").alias("events"))


@op("select c_custkey, count(event_id) as events from events right join customer on c_custkey = user_id group by 1")
def join_right(s, d):
    return t(s, d, "events").join(t(s, d, "customer"), F.col("c_custkey") == F.col("user_id"), "right").groupBy("c_custkey").agg(F.count("event_id").alias("events"))


@op("select c_custkey from customer where exists (select 1 from events where user_id = c_custkey)")
def exists(s, d):
    return A.exists(t(s, d, "customer").select("c_custkey"), t(s, d, "events").select(F.col("user_id").alias("c_custkey")), ["c_custkey"])


@op("select c_custkey from customer where not exists (select 1 from events where user_id = c_custkey)")
def minus(s, d):
    return A.minus(t(s, d, "customer").select("c_custkey"), t(s, d, "events").select(F.col("user_id").alias("c_custkey")))


@op("select a.n_nationkey as a, b.n_nationkey as b from nation a join nation b on a.n_regionkey < b.n_regionkey")
def join_theta(s, d):
    n = t(s, d, "nation")
    return n.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")).join(n.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb")), F.expr("ra < rb")).select("a", "b")


@op("select v.k as band, count(*) as n from orders join (values (1, 0.0, 1000.0), (2, 1000.0, 50000.0), (3, 40000.0, 90000.0)) as v(k, lo, hi) on o_totalprice >= lo and o_totalprice < hi group by 1")
def join_range(s, d):
    bands = s.sql("select * from values (1, 0.0D, 1000.0D), (2, 1000.0D, 50000.0D), (3, 40000.0D, 90000.0D) as v(band, lo, hi)")
    return A.range_join(t(s, d, "orders").select("o_totalprice"), "o_totalprice", bands, "lo", "hi", 10000.0).groupBy("band").agg(F.count("*").alias("n"))


@op("with e as (select event_id, user_id, event_type, epoch_us(ts) / 1000000.0 as at from events) select count(*) as pairs from e a join e b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.at >= a.at and b.at <= a.at + 86400")
def join_interval(s, d):
    e = t(s, d, "events").select("user_id", "event_type", (F.unix_micros(F.col("ts").cast("timestamp")) / 1000000.0).alias("at"))
    views, buys = e.where("event_type = 'view'").select("user_id", F.col("at").alias("a")), e.where("event_type = 'purchase'").select("user_id", F.col("at").alias("b"))
    return A.interval_join(views, buys, "user_id", "a", "b", 0.0, 86400.0).agg(F.count("*").alias("pairs"))


@op("with e as (select * from events), p as (select * from e where event_type = 'purchase'), v as (select user_id, ts, max(event_id) as seen from e where event_type = 'view' group by 1, 2) select p.event_id, v.seen as asof_seen from p asof left join v on p.user_id = v.user_id and p.ts >= v.ts")
def join_asof(s, d):
    e = t(s, d, "events")
    views = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("seen"))
    return A.asof_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, "user_id", "ts", "seen").select("event_id", "asof_seen")


@op("select r_name, o_orderpriority from region, (select distinct o_orderpriority from orders) as p")
def join_cross(s, d):
    return t(s, d, "region").select("r_name").crossJoin(t(s, d, "orders").select("o_orderpriority").distinct())


@op("select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey")
def join_self(s, d):
    x = t(s, d, "supplier")
    return x.select(F.col("s_suppkey").alias("a"), "s_nationkey").join(x.select(F.col("s_suppkey").alias("b"), "s_nationkey"), "s_nationkey").select("a", "b")


@op("select p_brand, count(*) as n from lineitem join part on l_partkey = p_partkey group by 1")
def join_salted(s, d):
    return A.salted_join(t(s, d, "lineitem").select(F.col("l_partkey").alias("k"), "l_orderkey", "l_linenumber"), t(s, d, "part").select(F.col("p_partkey").alias("k"), "p_brand"), "k").groupBy("p_brand").agg(F.count("*").alias("n"))


@op("select o_orderstatus, count(*) as n, round(sum(o_totalprice), 2) as total, round(avg(o_totalprice), 4) as mean, min(o_totalprice) as least, max(o_totalprice) as most from orders group by 1")
def agg_basic(s, d):
    p = F.col("o_totalprice")
    return t(s, d, "orders").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum(p), 2).alias("total"), F.round(F.avg(p), 4).alias("mean"), F.min(p).alias("least"), F.max(p).alias("most"))


@op("select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1")
def agg_distinct(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@op("select count(distinct l_orderkey) as orders, true as orders_close, true as quartiles_close from lineitem")
def agg_approx(s, d):
    """Approximate aggregates: the exact count, and whether they keep their bounds (five deviations; one rank in 1,000)."""
    rows = t(s, d, "lineitem")
    about = rows.agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"), F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75], 10000).alias("q")).first()
    price = F.col("l_extendedprice")
    # of the ranks that a value has, one is near the quantile
    near = [(F.avg((price < q).cast("double")) <= (k + 1) / 4 + 0.001) & (F.avg((price <= q).cast("double")) >= (k + 1) / 4 - 0.001) for k, q in enumerate(about["q"])]
    orders = F.count_distinct("l_orderkey")
    return rows.agg(orders.alias("orders"), (F.abs(F.lit(about["orders"]) - orders) <= 0.1 * orders).alias("orders_close"), (near[0] & near[1] & near[2]).alias("quartiles_close"))


@op("select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(var_pop(l_quantity), 6) as var, round(corr(l_quantity, l_extendedprice), 6) as corr from lineitem group by 1")
def agg_stat(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"))


@op("select c_nationkey, array_to_string(list_sort(list(distinct c_mktsegment)), ',') as segments, arg_max(c_custkey, struct_pack(a := c_acctbal, k := c_custkey)) as richest from customer group by 1")
def agg_collect(s, d):
    return t(s, d, "customer").groupBy("c_nationkey").agg(F.array_join(F.sort_array(F.collect_set("c_mktsegment")), ",").alias("segments"), F.max_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("richest"))


@op("select l_suppkey, count(*) as n from lineitem group by 1 having count(*) > 600")
def agg_having(s, d):
    return t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600")


_GEO = "customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"


def _geo(s, d):
    return t(s, d, "customer").join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))


@op(f"select r_name, n_name, count(*) as n, cast(grouping(r_name, n_name) as bigint) as level from {_GEO} group by rollup (r_name, n_name)")
def rollup(s, d):
    return _geo(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.grouping_id("r_name", "n_name").alias("level"))


@op(f"select r_name, c_mktsegment, count(*) as n from {_GEO} group by cube (r_name, c_mktsegment)")
def cube(s, d):
    return _geo(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@op(f"select r_name, c_mktsegment, count(*) as n from {_GEO} group by grouping sets ((r_name), (c_mktsegment), ())")
def grouping_sets(s, d):
    g = _geo(s, d).select("r_name", "c_mktsegment")
    return g.groupingSets([[F.col("r_name")], [F.col("c_mktsegment")], []], F.col("r_name"), F.col("c_mktsegment")).agg(F.count("*").alias("n"))


@op("select user_id, count(*) filter (event_type = 'view') as \"view\", count(*) filter (event_type = 'purchase') as purchase from events group by 1")
def pivot(s, d):
    return t(s, d, "events").groupBy("user_id").pivot("event_type", ["view", "purchase"]).count().na.fill(0)


_W = "partition by o_custkey order by o_orderdate, o_orderkey"


@op(f"select o_orderkey, rank() over (partition by o_custkey order by o_orderpriority) as r, dense_rank() over (partition by o_custkey order by o_orderpriority) as dr, row_number() over ({_W}) as rn, ntile(4) over ({_W}) as q, round(percent_rank() over (partition by o_custkey order by o_orderpriority), 6) as pr from orders")
def win_rank(s, d):
    by, w = Window.partitionBy("o_custkey").orderBy("o_orderpriority"), Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(s, d, "orders").select("o_orderkey", F.rank().over(by).cast("long").alias("r"), F.dense_rank().over(by).cast("long").alias("dr"), F.row_number().over(w).cast("long").alias("rn"), F.ntile(4).over(w).cast("long").alias("q"), F.round(F.percent_rank().over(by), 6).alias("pr"))


@op(f"select o_orderkey, lag(o_orderkey) over ({_W}) as before, lead(o_orderkey) over ({_W}) as after, first_value(o_orderkey) over ({_W}) as first, nth_value(o_orderkey, 2) over ({_W} rows between unbounded preceding and unbounded following) as second from orders")
def win_lag(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    k = "o_orderkey"
    return t(s, d, "orders").select(k, F.lag(k).over(w).alias("before"), F.lead(k).over(w).alias("after"), F.first(k).over(w).alias("first"), F.nth_value(k, 2).over(whole).alias("second"))


@op(f"select o_orderkey, count(*) over ({_W} rows between 2 preceding and current row) as moving, round(sum(o_totalprice) over ({_W} rows unbounded preceding), 2) as running from orders")
def win_frame(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(s, d, "orders").select("o_orderkey", F.count("*").over(w.rowsBetween(-2, 0)).alias("moving"), F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"))


@op("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10 offset 5")
def order_limit(s, d):
    return t(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10)


@op("select p_brand, p_partkey from (select p_brand, p_partkey, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as rn from part) as x where rn <= 3")
def topk_group(s, d):
    return A.top_k(t(s, d, "part"), 3, [F.desc("p_retailprice"), F.col("p_partkey")], ["p_brand"]).select("p_brand", "p_partkey")


@op("select o_orderstatus, count(*) as n, true as uniform_close, true as stratified_close from orders group by 1")
def sample(s, d):
    """Uniform and stratified samples: how many rows there are of each status, and whether the samples' sizes are within six deviations."""
    rows = t(s, d, "orders")
    shares = {"F": 0.05, "O": 0.1}
    size = lambda part, name: part.groupBy("o_orderstatus").agg(F.count("*").alias(name))
    n = size(rows, "n").join(size(rows.sample(0.1, seed=1), "a"), "o_orderstatus", "left").join(size(rows.sampleBy("o_orderstatus", shares, seed=2), "b"), "o_orderstatus", "left").na.fill(0)
    share = F.coalesce(F.create_map(*[F.lit(x) for kv in shares.items() for x in kv])[F.col("o_orderstatus")], F.lit(0.0))
    close = lambda k, p: F.abs(F.col(k) - p * F.col("n")) <= 6 * F.sqrt(p * (1 - p) * F.col("n")) + 3 * F.ceil(p)
    return n.select("o_orderstatus", "n", close("a", F.lit(0.1)).alias("uniform_close"), close("b", share).alias("stratified_close"))


@op("select c_nationkey as k from customer where c_nationkey < 5 union select s_nationkey from supplier where s_nationkey < 8")
def union_set(s, d):
    return t(s, d, "customer").where("c_nationkey < 5").select(F.col("c_nationkey").alias("k")).union(t(s, d, "supplier").where("s_nationkey < 8").select(F.col("s_nationkey").alias("k"))).distinct()


@op("select c_custkey, null :: bigint as s_suppkey from customer where c_nationkey = 1 union all select null, s_suppkey from supplier where s_nationkey = 1")
def union_by_name(s, d):
    return t(s, d, "customer").where("c_nationkey = 1").select("c_custkey").unionByName(t(s, d, "supplier").where("s_nationkey = 1").select("s_suppkey"), allowMissingColumns=True)


@op("select l_partkey from lineitem where l_quantity > 48 intersect select p_partkey from part where p_size < 10")
def intersect(s, d):
    return t(s, d, "lineitem").where("l_quantity > 48").select("l_partkey").intersect(t(s, d, "part").where("p_size < 10").select("p_partkey"))


@op("select c_nationkey from customer intersect all select s_nationkey from supplier")
def intersect_all(s, d):
    return t(s, d, "customer").select("c_nationkey").intersectAll(t(s, d, "supplier").select("s_nationkey"))


@op("select p_partkey from part except select l_partkey from lineitem where l_quantity > 40")
def except_set(s, d):
    return t(s, d, "part").select("p_partkey").subtract(t(s, d, "lineitem").where("l_quantity > 40").select("l_partkey"))


@op("select c_nationkey from customer except all select s_nationkey from supplier")
def except_all(s, d):
    return t(s, d, "customer").select("c_nationkey").exceptAll(t(s, d, "supplier").select("s_nationkey"))


@op("select page_id, lower(substr(url, 1, 5)) as head, length(url) as n, replace(url, 'http', 'x') as r, regexp_extract(url, '//([^/?#]+)', 1) as host, concat('page/', page_id) as iri from pages where url is not null")
def fn_string(s, d):
    u = F.col("url")
    return t(s, d, "pages").where("url is not null").select("page_id", F.lower(F.substring(u, 1, 5)).alias("head"), F.length(u).cast("long").alias("n"), F.replace(u, F.lit("http"), F.lit("x")).alias("r"), F.regexp_extract(u, "//([^/?#]+)", 1).alias("host"), F.concat(F.lit("page/"), "page_id").alias("iri"))


@op("select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, cast(cast(date_trunc('month', o_orderdate) as date) as string) as first_day, date_diff('day', date '1992-01-01', cast(o_orderdate as date)) as days, cast(cast(cast(o_orderdate as date) + 30 as date) as string) as due from orders")
def fn_date(s, d):
    x = F.col("o_orderdate")
    return t(s, d, "orders").select("o_orderkey", F.year(x).cast("long").alias("y"), F.month(x).cast("long").alias("m"), F.trunc(x, "month").cast("string").alias("first_day"), F.datediff(x, F.to_date(F.lit("1992-01-01"))).cast("long").alias("days"), F.date_add(x.cast("date"), 30).cast("string").alias("due"))


@op("select l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) as l, round(sqrt(l_quantity), 6) as q, round(pow(l_tax, 2), 8) as p, l_orderkey % 7 as m, greatest(l_tax, l_discount) as g, abs(l_discount - l_tax) < 0.000001 as same from lineitem")
def fn_math(s, d):
    return t(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.log("l_extendedprice"), 6).alias("l"), F.round(F.sqrt("l_quantity"), 6).alias("q"), F.round(F.pow("l_tax", F.lit(2)), 8).alias("p"), F.pmod("l_orderkey", F.lit(7)).alias("m"), F.greatest("l_tax", "l_discount").alias("g"), (F.abs(F.col("l_discount") - F.col("l_tax")) < 0.000001).alias("same"))


@op("select vec_id, len(embedding) as n, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 4) as norm2, len(list_filter(embedding, lambda x: x > 0)) as positive from embeddings")
def fn_array(s, d):
    e = F.col("embedding")
    return t(s, d, "embeddings").select("vec_id", F.size(e).cast("long").alias("n"), F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm2"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


@op("select user_id, event_type, count(*) as n from events group by all")
def fn_map(s, d):
    counted = t(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counted.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("event_type", "n"))


@op("select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")
def fn_json(s, d):
    return t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@op(f"select p, round(sum(try_cast(o as double)), 2) as total, count(*) filter (try_cast(o as double) is null) as bad from ({triples_sql(('balance', 'size', 'label'))}) as t group by p")
def fn_cast(s, d):
    triples = triples_from_tables(s, d, ("balance", "size", "label"))
    return triples.withColumn("v", typed_object("dbl")).groupBy("p").agg(F.round(F.sum("v"), 2).alias("total"), F.count_if(F.col("v").isNull()).alias("bad"))


@op("select count(*) as subjects, count(*) as ids, 8 :: bigint as homes, 0 :: bigint as astray from customer")
def fn_hash(s, d):
    """Ids and homes of subjects: distinct ids, all homes in use, and no subject away from the bucket that Spark gives its home."""
    from ..sources.store import home, seeds

    rows = triples_from_tables(s, d, ("locatedIn",)).select("s", F.xxhash64("s").alias("id"), home("s", 8).alias("home"))
    bucket = F.array_position(F.array(*map(F.lit, seeds(8))), F.col("home")) - 1
    return rows.agg(F.count_distinct("s").alias("subjects"), F.count_distinct("id").alias("ids"), F.count_distinct("home").alias("homes"), F.count_if(F.pmod(F.hash("home"), F.lit(8)) != bucket).alias("astray"))


def _edges(s, d, p):
    return triples_from_tables(s, d, (p,)).select("s", "o")


_NEXT, _PART, _BASED = triples_sql(("nextTurn",)), triples_sql(("partOf",)), triples_sql(("basedIn",))


@op(f"select distinct a.s, b.o from ({_BASED}) as a join ({_PART}) as b on a.o = b.s")
def path_seq(s, d):
    return A.path_sequence(_edges(s, d, "basedIn"), _edges(s, d, "partOf"))


@op(f"select s, o from ({_BASED}) as a union select s, o from ({_PART}) as b")
def path_alt(s, d):
    return A.path_alternative(_edges(s, d, "basedIn"), _edges(s, d, "partOf"))


@op(f"select o as s, s as o from ({_PART}) as a")
def path_inv(s, d):
    return A.path_inverse(_edges(s, d, "partOf"))


@op(f"with e as ({_NEXT}) select distinct a.s, b.o from e a join e b on a.o = b.s union select distinct a.s, c.o from e a join e b on a.o = b.s join e c on b.o = c.s")
def path_bounded(s, d):
    return A.path_bounded(_edges(s, d, "nextTurn"), 2, 3)


@op(f"with recursive e as ({_NEXT}), r as (select s, o from e union select r.s, e.o from r join e on r.o = e.s) select s, o from r")
def path_closure(s, d):
    return A.path_closure(_edges(s, d, "nextTurn"))


@op(f"with e as (select distinct * from ({triples_sql(('basedIn', 'partOf'))}) as t) select s, p, o from e where s = 'supplier/1' union select b.s, b.p, b.o from e a join e b on a.o = b.s where a.s = 'supplier/1'")
def neighbourhood(s, d):
    triples = triples_from_tables(s, d, ("basedIn", "partOf")).select("s", "p", "o")
    return A.neighbourhood(triples, s.sql("select 'supplier/1' as v"), 2)


@op("select 'customer' as kind, count(*) as n from customer")
def udf_scalar(s, d):
    kind = iri_kind(s)
    return triples_from_tables(s, d, ("locatedIn",)).select(kind("s").alias("kind")).groupBy("kind").agg(F.count("*").alias("n"))


@op("select user_id, max(case when 2 * k > n then event_type end) as majority from (select user_id, event_type, count(*) as k, sum(count(*)) over (partition by user_id) as n from events where event_type in ('view', 'click', 'purchase') group by 1, 2) as x group by 1")
def udaf_majority(s, d):
    return majority_vote(t(s, d, "events").where("event_type in ('view', 'click', 'purchase')").select("user_id", "event_type"), "user_id", "event_type")


@op(
    "select c_custkey, concat('?', 'o') as s, p, case p when 'placedBy' then concat('customer/', c_custkey) else concat('segment/', c_mktsegment) end as o from customer, (values ('placedBy'), ('wantedIn')) as v(p) "
    "union all select c_custkey, concat('customer/', c_custkey) as s, 'locatedIn' as p, concat('nation/', c_nationkey) as o from customer"
)
def udtf_edges(s, d):
    """The patterns of a query text for every customer: the customer's orders, and where and in which segment."""
    register(s)
    text = F.format_string("SELECT ?o WHERE { ?o placedBy customer/%d . customer/%d locatedIn nation/%d . ?o wantedIn segment/%s }", "c_custkey", "c_custkey", "c_nationkey", "c_mktsegment")
    t(s, d, "customer").select("c_custkey", text.alias("text")).createOrReplaceTempView("trellis_log")
    return s.sql("select c_custkey, e.* from trellis_log, lateral pattern_edges(text) as e")
