"""The systems that the engine is compared with, as ways of placing and joining on Spark."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators.evaluate import Options, Traffic, connected, distributed, local_join, plain, plain_of
from .plans.patterns import BGP, Const, Pattern, Var
from .session import checkpointed, shared_folder, shuffles_freed
from .sources.store import Store, TableStore, home, prepare, seeds
from .sources.vocab import NUMBERS, Mapping, Star, mapped, prefix_of, stars_of


def _scan(triples: DataFrame) -> Callable[[Pattern], DataFrame]:
    """Bindings of a pattern from a plain table (s, p, o)."""

    def answer(p: Pattern) -> DataFrame:
        rows, columns = triples, {}
        for slot, t in (("s", p.s), ("p", p.p), ("o", p.o)):
            if isinstance(t, Const):
                rows = rows.where(F.col(slot) == t.value)
            elif t.name in columns:
                rows = rows.where(F.col(slot) == columns[t.name])
            else:
                columns[t.name] = F.col(slot)
        return rows.select(*[c.alias(v) for v, c in columns.items()])

    return answer


def _written(df: DataFrame) -> DataFrame:
    """A stage's result as a table in the shared folder: the stages of a batch job, one join each."""
    path = f"{shared_folder(df.sparkSession)}/stage-{uuid.uuid4().hex}"
    with shuffles_freed(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def staged(scan: Callable[[Pattern], DataFrame], bgp: BGP, hint: str) -> DataFrame:
    """Joins in text order, reduce-side, with every intermediate result written and read again."""
    connected(bgp)
    left, out, have = list(bgp.patterns), None, set()
    while left:
        p = next((p for p in left if have & set(p.variables)), left[0])
        left.remove(p)
        right = scan(p)
        shared = [v for v in p.variables if v in have]
        out = right if out is None else _written(out.join(right.hint(hint), shared))
        have |= set(p.variables)
    return out


def batch_random(triples: DataFrame, bgp: BGP, workers: int) -> DataFrame:
    """Random placement, one reduce-side join a stage."""
    return staged(_scan(triples.select("s", "p", "o").repartition(workers)), bgp, "shuffle_hash")


def batch_range(triples: DataFrame, bgp: BGP, workers: int) -> DataFrame:
    """Range placement, merge joins, one a stage."""
    return staged(_scan(triples.select("s", "p", "o").repartitionByRange(workers, "s")), bgp, "merge")


def khop(triples: DataFrame, k: int, workers: int, direction: str = "forward", type_opt: bool = True, prefix: bool = False, predicate: str = "type") -> DataFrame:
    """(home, s, p, o): every home holds what lies within k hops of its subjects.

    forward follows objects, undirected also subjects; with the type option nothing is reached
    through classes; with `prefix` homes go by the name before the last slash (semantic hashing).
    """
    key = F.substring_index("s", "/", 1) if prefix else F.col("s")
    have = triples.select(home(key, workers).alias("home"), "s", "p", "o")
    all_triples = triples.select("s", "p", "o")
    for _ in range(k - 1):
        through = have.where(F.col("p") != predicate) if type_opt else have
        edge = through.select("home", F.col("o").alias("v")).distinct()
        reached = edge.join(all_triples, F.col("v") == F.col("s")).select("home", "s", "p", "o")
        if direction == "undirected":
            back = through.select("home", F.col("s").alias("v")).distinct()
            inward = all_triples.where(F.col("p") != predicate) if type_opt else all_triples
            reached = reached.union(back.join(inward, F.col("v") == F.col("o")).select("home", "s", "p", "o"))
        have = checkpointed(have.union(reached).distinct())
    return have


def _can_name(m: Mapping, prefix: str) -> bool:
    """Whether an object of the mapping can be a subject whose name begins with the prefix."""
    known = prefix_of(m.object)
    return m.kind not in NUMBERS and (known.startswith(prefix) or prefix.startswith(known))


def khop_replicas(store: TableStore, kind: str, bgp: BGP) -> DataFrame:
    """(home, s, p, o): of the two-hop placement of the whole graph, the triples that the query's patterns can match.

    The same rows as `khop` has of these mappings: what a home reaches is told from all predicates'
    triples, as homes by the name that they reach, and copied for each entity once; only what is
    asked for is then replicated. Raw columns are read; whole copies of the graph aren't made.
    """
    spark, workers, key = store.spark, store.workers, lambda s: F.substring_index(s, "/", 1) if kind == "khop_prefix" else s
    homes, mappings = seeds(workers), list(store.units.values())

    def through(ends: Callable[[Mapping], bool]) -> list[DataFrame]:
        return [mapped(spark, store.sf_dir, m) for m in mappings if m.predicate != "type" and ends(m)]

    def flagged(rows: DataFrame, v: str, prefix: str) -> DataFrame:
        """(v, a flag for each home): a row for each name, in which homes it is met; partial sums travel."""
        at = rows.where(F.col(v).startswith(prefix)).select(F.col(v).alias("v"), home(key(F.col("s")), workers).alias("h"))
        return at.groupBy("v").agg(*[F.bool_or(F.col("h") == h).alias(f"at{k}") for k, h in enumerate(homes)])

    def told(parts: list[DataFrame], v: str, prefix: str) -> DataFrame:
        """Each mapping's flags are made by themselves, so that one table's shuffle files are there at a time."""
        path = f"{shared_folder(spark)}/reach-{uuid.uuid4().hex}"
        with shuffles_freed(spark):
            for rows in parts:
                flagged(rows, v, prefix).write.mode("append").parquet(path)
        names = [f"at{k}" for k in range(workers)]
        schema = f"v string, {', '.join(f'{n} boolean' for n in names)}"
        if not parts:
            return spark.createDataFrame([], schema)
        return spark.read.schema(schema).parquet(path).groupBy("v").agg(*[F.bool_or(n).alias(n) for n in names])

    def with_homes(rows: DataFrame, reach: DataFrame, end: str) -> DataFrame:
        """Rows with the homes that reach their end added to those they have."""
        also = F.filter(F.array(*[F.when(F.col(f"at{k}"), F.lit(h)) for k, h in enumerate(homes)]), lambda h: h.isNotNull())
        met = rows.join(reach.select(F.col("v").alias(end), also.alias("__also")), end, "left")
        return met.withColumn("__homes", F.array_union("__homes", F.coalesce("__also", F.array().cast("array<int>")))).select("s", "o", "__homes")

    units = [store.units[u] for u in dict.fromkeys(u for p in bgp for u in (store.able(p) if isinstance(p.p, Const) else store.units))]
    reached: dict[str, DataFrame] = {}
    subjects: dict[str, DataFrame] = {}
    path = f"{shared_folder(spark)}/replicas-{uuid.uuid4().hex}"
    for m in units:
        prefix = prefix_of(m.subject)
        if prefix not in reached:
            reached[prefix] = told(through(lambda x, prefix=prefix: _can_name(x, prefix)), "o", prefix)
        rows = with_homes(mapped(spark, store.sf_dir, m).repartition("s").distinct().withColumn("__homes", F.array(home(key(F.col("s")), workers))), reached[prefix], "s")
        if kind == "khop_undirected" and m.predicate != "type" and m.kind not in NUMBERS:
            ends = prefix_of(m.object)
            if ends not in subjects:
                subjects[ends] = told(through(lambda x, ends=ends: prefix_of(x.subject).startswith(ends) or ends.startswith(prefix_of(x.subject))), "s", ends)
            rows = with_homes(rows, subjects[ends], "o")
        placed = rows.select(F.explode("__homes").alias("home"), "s", F.lit(m.predicate).alias("p"), "o")
        with shuffles_freed(spark):
            placed.repartition(workers, "home").sortWithinPartitions("home", "p", "s").write.mode("append").option("compression", "zstd").parquet(path)
    return spark.read.schema("home int, s string, p string, o string").parquet(path)


def radius(bgp: BGP, forward: bool = True) -> tuple[Var | Const | None, float]:
    """The term from which the fewest hops reach all patterns, and their number; infinite if none does."""
    terms = list(dict.fromkeys(t for p in bgp for t in (p.s, p.o)))
    best: tuple[Var | Const | None, float] = (None, math.inf)
    for root in terms:
        at = {root: 0}
        for _ in range(len(bgp)):
            for p in bgp:
                if p.s in at:
                    at[p.o] = min(at.get(p.o, math.inf), at[p.s] + 1)
                if not forward and p.o in at:
                    at[p.s] = min(at.get(p.s, math.inf), at[p.o] + 1)
        need = max((at[p.s] + 1 if p.s in at else math.inf) if forward else min(at.get(p.s, math.inf), at.get(p.o, math.inf)) + 1 for p in bgp)
        if need < best[1]:
            best = (root, need)
    return best


def khop_answer(store: Store, replicas: Callable[[], DataFrame], bgp: BGP, k: int, workers: int, forward: bool = True, prefix: bool = False) -> tuple[DataFrame, str]:
    """Parallel where k hops from a subject hold the whole query, else as batch stages over all triples.

    Answers are taken from the home of the query's centre, so that replicas don't repeat them.
    """
    root, need = radius(bgp, forward)
    if need > k or root is None or not any(p.s == root for p in bgp):
        return plain_of(store, bgp), "distributed"
    left, out, replicated = list(bgp.patterns), None, replicas()

    def at_home(p: Pattern) -> DataFrame:
        columns = {t.name: F.col(s).alias(t.name) for s, t in (("o", p.o), ("p", p.p), ("s", p.s)) if isinstance(t, Var)}
        rows = replicated
        for s, t in (("s", p.s), ("p", p.p), ("o", p.o)):
            rows = rows.where(F.col(s) == t.value) if isinstance(t, Const) else rows
        return rows.select("home", *columns.values())

    have: set[str] = set()
    while left:
        p = next((p for p in left if have & set(p.variables)), left[0])
        left.remove(p)
        right = at_home(p)
        out = right if out is None else local_join(out, right)
        have |= set(p.variables)
    key = F.col(root.name) if isinstance(root, Var) else F.lit(root.value)
    return out.where(F.col("home") == home(F.substring_index(key, "/", 1) if prefix else key, workers)).drop("home"), "parallel"


#: Rows that are sent in one go, each for one object of a home: shuffle files of so many are there at a time, of an eighth at least.
VOTES = 1 << 24
#: Edges in a bucket of the partitioner, which one task works off.
BUCKET = 1 << 21


class _Bucketed:
    """A table whose rows lie by `home` in as many buckets; it is appended to in portions, and let go with its files."""

    def __init__(self, spark: SparkSession, buckets: int):
        self.spark, self.buckets, tag = spark, buckets, uuid.uuid4().hex
        self.name, self.folder = f"trellis_parts_{tag[:12]}", f"{shared_folder(spark)}/parts-{tag}"

    def add(self, rows: DataFrame, *order: str) -> _Bucketed:
        with shuffles_freed(self.spark):
            rows = rows.sortWithinPartitions("home", *order) if order else rows
            rows.write.mode("append").bucketBy(self.buckets, "home").option("path", self.folder).option("compression", "zstd").saveAsTable(self.name)
        return self

    @property
    def rows(self) -> DataFrame:
        return self.spark.table(self.name)

    def drop(self) -> None:
        self.spark.sql(f"drop table if exists {self.name}")
        where = self.spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)


def min_cut(triples: DataFrame | list[Star], parts: int, rounds: int = 5, slack: float = 1.1, seed: int = 1) -> DataFrame:
    """(v, part): label propagation under a cap on the size of parts, from a hash start; v is the xxhash64 of a vertex's name.

    A vertex asks for the part that most of its neighbours have; of a part's askers as many move as
    its room admits, by a hash, so that sizes stay within the cap. A triple that repeats votes each
    time; names of one hash share their part, which no answer depends on.

    Names are read and hashed once: a table's rows are kept by the home of their subject, with all
    the objects that they give it. What a home has to tell an object is counted there, and sent once
    for each object; an object's part comes back once for each home that asks, and is met there.
    """
    stars = [Star(triples.select("s", "o"), "s", ("o",))] if isinstance(triples, DataFrame) else triples
    spark = stars[0].source.sparkSession
    prepare(spark)
    counts = [x.source.agg(F.count("*").alias("n")).withColumn("k", F.lit(k)) for k, x in enumerate(stars)]
    with shuffles_freed(spark):
        ends = {r["k"]: r["n"] * len(stars[r["k"]].objects) for r in reduce(DataFrame.union, counts).collect()}
    buckets = max(parts, math.ceil(sum(ends.values()) / BUCKET))
    objects = [f"o{k}" for k in range(max(len(x.objects) for x in stars))]
    graph = _Bucketed(spark, buckets)

    def hashed(x: Star) -> DataFrame:
        own = {f"o{k}": F.when(F.expr(f"({o}) is not null"), F.xxhash64(F.expr(o))) for k, o in enumerate(x.objects)}
        return x.source.where(f"({x.subject}) is not null").select(F.xxhash64(F.expr(x.subject)).alias("s"), *[own.get(o, F.lit(None).cast("bigint")).alias(o) for o in objects])

    jobs: list[list[Star]] = [[]]
    room = BUCKET
    for k in sorted(ends, key=ends.get):  # small tables together
        if jobs[-1] and ends[k] > room:
            jobs.append([])
            room = BUCKET
        jobs[-1].append(stars[k])
        room -= ends[k]
    for job in jobs:
        graph.add(reduce(DataFrame.union, map(hashed, job)).withColumn("home", home("s", buckets)).repartition(buckets, "home"))

    def edges(rows: DataFrame) -> DataFrame:
        """The rows with one object each, loops left out."""
        return rows.withColumn("o", F.explode(F.array(*objects))).drop(*objects).where("o is not null and o != s")

    def met(rows: DataFrame, table: DataFrame, end: str) -> DataFrame:
        """Rows with what a table has of their vertex, at its home."""
        return rows.join(table.withColumnRenamed("v", end).hint("shuffle_hash"), ["home", end])

    # which homes ask for an object's part
    asks = edges(graph.rows).groupBy("home", "o").agg(F.lit(1).alias("one")).select(F.col("home").alias("origin"), home("o", buckets).alias("home"), "o")
    asked = _Bucketed(spark, buckets).add(asks.repartition(buckets, "home"), "o")
    portions = min(8, max(1, math.ceil(asked.rows.count() / VOTES)))
    ties = graph.rows.where(reduce(lambda a, b: a | b, [F.col(o).isNotNull() & (F.col(o) != F.col("s")) for o in objects]))
    subjects, named = (x.groupBy("home", F.col(end).alias("v")).agg(F.lit(1).alias(f"of_{end}")) for x, end in ((ties, "s"), (asked.rows, "o")))
    state = _Bucketed(spark, buckets).add(subjects.join(named.hint("shuffle_hash"), ["home", "v"], "full").select("home", "v"))
    cap = math.ceil(slack * state.rows.count() / parts)
    label = state.rows.withColumn("part", F.pmod(F.xxhash64(F.lit(seed), "v"), F.lit(parts)).cast("int"))
    each = [F.count_if(F.col("part") == k).alias(f"n{k}") for k in range(parts)]
    names = [f"n{k}" for k in range(parts)]
    luck = lambda r: F.pmod(F.xxhash64(F.lit(r), "v"), F.lit(1_000_000)) / 1_000_000
    for r in range(rounds):
        told = _Bucketed(spark, buckets)  # votes of subjects, at their objects' homes
        for k in range(portions):
            spoken = edges(met(graph.rows, label, "s"))
            spoken = spoken.where(F.pmod("o", F.lit(portions)) == k) if portions > 1 else spoken
            votes = spoken.groupBy("home", "o").agg(*each)
            sent = votes.select(home("o", buckets).alias("home"), "o", *names).repartition(buckets, "home")
            told.add(sent.groupBy("home", F.col("o").alias("v")).agg(*[F.sum(n).alias(n) for n in names]))
        after = _Bucketed(spark, buckets)
        for k in range(portions):  # votes of objects, at their subjects' homes; a portion of homes at a time
            here = [h for i, h in enumerate(seeds(buckets)) if i % portions == k]
            heard = met(asked.rows.where(F.col("origin").isin(here)), label, "o").select(F.col("origin").alias("home"), "o", "part").repartition(buckets, "home")
            votes = edges(graph.rows.where(F.col("home").isin(here))).join(heard.hint("shuffle_hash"), ["home", "o"]).groupBy("home", F.col("s").alias("v")).agg(*each)
            both = label.where(F.col("home").isin(here))
            for x, mark in ((votes, "s"), (told.rows.where(F.col("home").isin(here)), "o")):
                both = both.join(x.select("home", "v", *[F.col(n).alias(f"{mark}{n}") for n in names]).hint("shuffle_hash"), ["home", "v"], "left")
            count = lambda n: F.coalesce(f"s{n}", F.lit(0)) + F.coalesce(f"o{n}", F.lit(0))
            best = F.array_max(F.array(*[F.struct(count(n).alias("n"), F.xxhash64(F.lit(i), F.lit(r)).alias("tie"), F.lit(i).alias("part")) for i, n in enumerate(names)]))
            after.add(both.select("home", "v", "part", best["part"].alias("wish")))
        told.drop()
        state.drop()
        state = after
        with shuffles_freed(spark):
            counted = state.rows.groupBy("part", "wish").agg(F.count("*").alias("n")).collect()  # `parts` squared rows
        sizes, asking = [0] * parts, [0] * parts
        for x in counted:
            sizes[x["part"]] += x["n"]
            asking[x["wish"]] += x["n"] * (x["part"] != x["wish"])
        share = F.element_at(F.array(*[F.lit(max(0.0, min(1.0, (cap - n) / max(m, 1)))) for n, m in zip(sizes, asking, strict=True)]), F.col("wish") + 1)
        label = state.rows.select("home", "v", F.when((F.col("part") != F.col("wish")) & (luck(r) < share), F.col("wish")).otherwise(F.col("part")).alias("part"))
    graph.drop()
    asked.drop()
    return label.select("v", "part")


def with_part(rows: DataFrame, label: DataFrame, end: str, name: str, how: str = "inner") -> DataFrame:
    """Rows with the part of the vertex that a column names."""
    return rows.join(label.select(F.col("v").alias("__v"), F.col("part").alias(name)), F.xxhash64(end) == F.col("__v"), how).drop("__v")


def edge_cut(triples: DataFrame, label: DataFrame) -> DataFrame:
    """One row: edges, cut edges, and their ratio, which is what one-hop replication of cut edges adds."""
    ends = with_part(with_part(triples.select("s", "o"), label, "s", "a"), label, "o", "b")
    return ends.agg(F.count("*").alias("edges"), F.count_if(F.col("a") != F.col("b")).alias("cut")).withColumn("ratio", F.col("cut") / F.col("edges"))


def cut_edges_replicated(triples: DataFrame, label: DataFrame) -> DataFrame:
    """(home, s, p, o, of_s, of_o): every triple at the parts of both its ends, so that a vertex has all its edges in its part."""
    ends = with_part(with_part(triples, label, "s", "of_s", "left"), label, "o", "of_o", "left")
    # a vertex that only meets itself has no part of its own
    ends = ends.withColumns({"of_s": F.coalesce("of_s", F.lit(0)), "of_o": F.coalesce("of_o", F.lit(0))})
    return ends.select(F.explode(F.array_distinct(F.array("of_s", "of_o"))).alias("home"), "s", "p", "o", "of_s", "of_o")


def min_cut_answer(store: Store, replicated: DataFrame, bgp: BGP) -> tuple[DataFrame, str]:
    """Parallel where one vertex touches all patterns, at the part of its binding; else by merge joins over all triples."""
    centre = next((t for t in dict.fromkeys(t for p in bgp for t in (p.s, p.o)) if all(t in (p.s, p.o) for p in bgp)), None)
    if centre is None:
        return plain_of(store, bgp), "distributed"
    connected(bgp)

    def at_home(p: Pattern) -> DataFrame:
        rows = replicated.where(F.col("home") == F.col("of_s" if p.s == centre else "of_o"))
        columns: dict[str, Column] = {}
        for slot, t in (("s", p.s), ("p", p.p), ("o", p.o)):
            if isinstance(t, Const):
                rows = rows.where(F.col(slot) == t.value)
            elif t.name in columns:
                rows = rows.where(F.col(slot) == F.col(columns[t.name]))
            else:
                columns[t.name] = slot
        return rows.select("home", *[F.col(slot).alias(v) for v, slot in columns.items()])

    return reduce(local_join, [at_home(p) for p in bgp]).drop("home"), "parallel"


def summary_graph(triples: DataFrame, label: DataFrame) -> DataFrame:
    """(a, p, b): which parts a predicate connects."""
    return with_part(with_part(triples, label, "s", "a"), label, "o", "b").select("a", "p", "b").distinct()


def pruned_by_summary(triples: DataFrame, label: DataFrame, bgp: BGP) -> DataFrame:
    """Join-ahead pruning: the query over the summary tells which parts can hold answers, before the triples are joined."""
    summary = checkpointed(summary_graph(triples, label)).select(F.col("a").alias("s"), "p", F.col("b").alias("o"))
    general = BGP(tuple(Pattern(p.s if isinstance(p.s, Var) else Var(f"c_{_name(p.s)}"), p.p, p.o if isinstance(p.o, Var) else Var(f"c_{_name(p.o)}")) for p in bgp))
    parts = checkpointed(plain(_scan(summary), general).distinct())
    tagged = with_part(with_part(triples, label, "s", "a"), label, "o", "b")

    def scan(p: Pattern) -> DataFrame:
        g = general.patterns[bgp.patterns.index(p)]
        may = parts.select(F.col(g.s.name).alias("a"), F.col(g.o.name).alias("b")).distinct()
        return _scan(tagged.join(may, ["a", "b"], "left_semi").select("s", "p", "o"))(p)

    return plain(scan, bgp)


def _name(c: Const) -> str:
    return "".join(x if x.isalnum() else "_" for x in c.value)


def merge_joins(store: Store, bgp: BGP) -> DataFrame:
    """Two index scans and a distributed merge join for each join; no keys are looked up."""
    return plain_of(store, bgp, "merge")


def explore(store: Store, bgp: BGP) -> DataFrame:
    """Graph exploration: candidates of each pattern are reduced forward by those before, then joined in one place."""
    connected(bgp)
    kept: list[DataFrame] = []
    seen: dict[str, DataFrame] = {}
    left, have = list(bgp.patterns), set()
    while left:
        p = next((p for p in left if have & set(p.variables)), left[0])
        left.remove(p)
        rows = store.answer(p).drop("home")
        for v in p.variables:
            if v in seen:
                rows = rows.join(seen[v], v, "left_semi")
        for v in p.variables:
            seen[v] = rows.select(v).distinct()
        kept.append(rows)
        have |= set(p.variables)
    out = kept[0].coalesce(1)
    for rows in kept[1:]:
        rows = rows.coalesce(1)
        shared = [c for c in rows.columns if c in out.columns]
        out = out.join(rows, shared)
    return out.coalesce(1)


def central(triples: DataFrame, bgp: BGP) -> DataFrame:
    """Everything in one partition."""
    return plain(_scan(triples.select("s", "p", "o").coalesce(1)), bgp).coalesce(1)


def broadcast_all(store: Store, bgp: BGP, traffic: Traffic | None = None) -> DataFrame:
    """No use of where subjects lie: every join's keys go to all homes."""
    return distributed(store, bgp, Options(locality=False), traffic).drop("home")


def triples_of(store: Store) -> DataFrame:
    return store.spark.table(store.ps).select("s", "p", "o")


def graph_of(store: Store) -> DataFrame | list[Star]:
    """(s, o) of the whole graph: where its tables are known, as rows of these, which places nothing."""
    if not isinstance(store, TableStore):
        return triples_of(store).select("s", "o")
    return stars_of(store.spark, store.sf_dir, store.units.values())


_PREPARED: dict[tuple[str, str], DataFrame] = {}


def prepared(store: Store, kind: str) -> DataFrame:
    """What a replicating or partitioning system builds before any query, over the whole graph: once for each store."""
    key = (store.key, kind)
    if key not in _PREPARED:
        if kind == "summary":
            _PREPARED[key] = min_cut(graph_of(store), store.workers)
        elif kind == "min_cut":
            _PREPARED[key] = _written(cut_edges_replicated(triples_of(store), prepared(store, "summary")).repartition(store.workers, "home"))
        else:
            placed = khop(triples_of(store), 2, store.workers, "undirected" if kind == "khop_undirected" else "forward", prefix=kind == "khop_prefix")
            _PREPARED[key] = _written(placed.repartition(store.workers, "home").sortWithinPartitions("home", "p", "s"))
    return _PREPARED[key]


def replicas_for(store: Store, kind: str, bgp: BGP) -> DataFrame:
    """The placement's triples that a query can match: of the whole placement where there is one already, or where nothing is known of the triples' source."""
    if not isinstance(store, TableStore) or (store.key, kind) in _PREPARED:
        return prepared(store, kind)
    key = (store.key, f"{kind}: {' '.join(dict.fromkeys(u for p in bgp for u in (store.able(p) if isinstance(p.p, Const) else store.units)))}")
    if key not in _PREPARED:
        if kind == "min_cut":
            _PREPARED[key] = _written(cut_edges_replicated(store.triples(bgp), prepared(store, "summary")).repartition(store.workers, "home"))
        else:
            _PREPARED[key] = khop_replicas(store, kind, bgp)
    return _PREPARED[key]


#: The systems that `answer` knows.
KINDS = ("batch_random", "batch_range", "khop", "khop_undirected", "khop_prefix", "min_cut", "summary", "merge", "explore", "central", "broadcast_all")


def answer(store: Store, kind: str, bgp: BGP) -> DataFrame:
    """A query by a comparison system that holds the whole graph."""
    if kind == "batch_random":
        return batch_random(store.triples(bgp), bgp, store.workers)
    if kind == "batch_range":
        return batch_range(store.triples(bgp), bgp, store.workers)
    if kind.startswith("khop"):
        return khop_answer(store, lambda: replicas_for(store, kind, bgp), bgp, 2, store.workers, forward=kind != "khop_undirected", prefix=kind == "khop_prefix")[0]
    if kind == "min_cut":
        return min_cut_answer(store, replicas_for(store, kind, bgp), bgp)[0]
    if kind == "summary":
        return pruned_by_summary(store.triples(bgp), prepared(store, kind), bgp)
    if kind == "central":
        return central(store.triples(bgp), bgp)
    return {"merge": merge_joins, "explore": explore, "broadcast_all": broadcast_all}[kind](store, bgp)


def replication(placed: DataFrame, originals: int) -> DataFrame:
    """One row: stored triples, and those beyond the originals as a share of them."""
    return placed.agg(F.count("*").alias("stored")).withColumn("ratio", (F.col("stored") - originals) / originals)


