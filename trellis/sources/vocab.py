"""Direct mapping of the relational tables to triples.

Each predicate is one row of the mapping: table, subject and object as SQL expressions that
Spark and DuckDB read alike, so that the same mapping gives the triples here and, as plain SQL
over the relational tables, the oracle of the tests.
"""

from __future__ import annotations

import re
from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_MONEY = "cast(cast({} as decimal(18,2)) as string)"
_DAY = "cast(cast({} as date) as string)"


@dataclass(frozen=True)
class Mapping:
    predicate: str
    table: str
    subject: str
    object: str
    kind: str = "iri"  # iri, str, int, dec or date
    where: str = ""

    @property
    def constant(self) -> str | None:
        """The object, where all triples of the mapping have the same."""
        found = re.fullmatch("'([^']*)'", self.object)
        return found and found[1]

    @property
    def files(self) -> tuple[str, ...]:
        """The tables that it reads."""
        return tuple(t for t in TABLES if re.search(rf"\b{t}\b", self.table))

    @property
    def sql(self) -> str:
        """Distinct (s, o) of the predicate from the relational tables."""
        return f"select distinct {self.subject} as s, {self.object} as o from {self.table}" + (f" where {self.where}" if self.where else "")


def _entity(name: str, *keys: str) -> str:
    parts = ", '-', ".join(keys)
    return f"concat('{name}/', {parts})"


_REGION, _NATION = _entity("region", "r_regionkey"), _entity("nation", "n_nationkey")
_CUSTOMER, _SUPPLIER, _PART, _ORDER = _entity("customer", "c_custkey"), _entity("supplier", "s_suppkey"), _entity("part", "p_partkey"), _entity("order", "o_orderkey")
_LINE = _entity("line", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
_EVENT, _DOC, _PAGE, _ITEM, _VEC = _entity("event", "event_id"), _entity("doc", "doc_id"), _entity("page", "page_id"), _entity("item", "item_id"), _entity("vec", "vec_id")
_TURN = _entity("turn", "conv_id", "turn")
_SOLD = "(select distinct o_custkey, l_partkey, l_suppkey from lineitem join orders on l_orderkey = o_orderkey) as sold"
_NEXT = "(select a.conv_id as conv_id, a.turn as turn, min(b.turn) as later from conversations a join conversations b on a.conv_id = b.conv_id and b.turn > a.turn group by a.conv_id, a.turn) as following"

MAPPINGS: tuple[Mapping, ...] = (
    *(Mapping("type", t, s, f"'class/{c}'") for t, s, c in (("region", _REGION, "Region"), ("nation", _NATION, "Nation"), ("customer", _CUSTOMER, "Customer"), ("supplier", _SUPPLIER, "Supplier"), ("part", _PART, "Part"), ("orders", _ORDER, "Order"), ("lineitem", _LINE, "Line"), ("events", _EVENT, "Event"), ("documents", _DOC, "Document"))),
    *(Mapping("label", t, s, o, "str") for t, s, o in (("region", _REGION, "r_name"), ("nation", _NATION, "n_name"), ("customer", _CUSTOMER, "c_name"), ("supplier", _SUPPLIER, "s_name"), ("part", _PART, "p_name"))),
    Mapping("partOf", "nation", _NATION, _entity("region", "n_regionkey")),
    Mapping("locatedIn", "customer", _CUSTOMER, _entity("nation", "c_nationkey")),
    Mapping("segment", "customer", _CUSTOMER, _entity("segment", "c_mktsegment")),
    Mapping("balance", "customer", _CUSTOMER, _MONEY.format("c_acctbal"), "dec"),
    Mapping("basedIn", "supplier", _SUPPLIER, _entity("nation", "s_nationkey")),
    Mapping("balance", "supplier", _SUPPLIER, _MONEY.format("s_acctbal"), "dec"),
    Mapping("brand", "part", _PART, _entity("brand", "p_brand")),
    Mapping("category", "part", _PART, _entity("category", "p_type")),
    Mapping("size", "part", _PART, "cast(p_size as string)", "int"),
    Mapping("price", "part", _PART, _MONEY.format("p_retailprice"), "dec"),
    Mapping("placedBy", "orders", _ORDER, _entity("customer", "o_custkey")),
    Mapping("status", "orders", _ORDER, _entity("status", "o_orderstatus")),
    Mapping("priority", "orders", _ORDER, _entity("priority", "o_orderpriority")),
    Mapping("orderDate", "orders", _ORDER, _DAY.format("o_orderdate"), "date"),
    Mapping("total", "orders", _ORDER, _MONEY.format("o_totalprice"), "dec"),
    Mapping("inOrder", "lineitem", _LINE, _entity("order", "l_orderkey")),
    Mapping("ofPart", "lineitem", _LINE, _entity("part", "l_partkey")),
    Mapping("fromSupplier", "lineitem", _LINE, _entity("supplier", "l_suppkey")),
    Mapping("returnFlag", "lineitem", _LINE, _entity("flag", "l_returnflag")),
    Mapping("lineStatus", "lineitem", _LINE, _entity("linestatus", "l_linestatus")),
    Mapping("quantity", "lineitem", _LINE, _MONEY.format("l_quantity"), "dec"),
    Mapping("extPrice", "lineitem", _LINE, _MONEY.format("l_extendedprice"), "dec"),
    Mapping("discount", "lineitem", _LINE, _MONEY.format("l_discount"), "dec"),
    Mapping("tax", "lineitem", _LINE, _MONEY.format("l_tax"), "dec"),
    Mapping("shipDate", "lineitem", _LINE, _DAY.format("l_shipdate"), "date"),
    Mapping("bought", _SOLD, _entity("customer", "o_custkey"), _entity("part", "l_partkey")),
    Mapping("boughtFrom", _SOLD, _entity("customer", "o_custkey"), _entity("supplier", "l_suppkey")),
    Mapping("supplies", "lineitem", _entity("supplier", "l_suppkey"), _entity("part", "l_partkey")),
    Mapping("byUser", "events", _EVENT, _entity("customer", "user_id")),
    Mapping("kind", "events", _EVENT, _entity("kind", "event_type")),
    Mapping("day", "events", _EVENT, _DAY.format("ts"), "date"),
    Mapping("value", "events", _EVENT, _MONEY.format("value"), "dec"),
    Mapping("inConversation", "conversations", _TURN, _entity("conversation", "conv_id")),
    Mapping("role", "conversations", _TURN, _entity("role", "role")),
    Mapping("nextTurn", _NEXT, _TURN, _entity("turn", "conv_id", "later")),
    Mapping("lang", "documents", _DOC, _entity("lang", "lang"), where="lang is not null"),
    Mapping("source", "documents", _DOC, _entity("source", "source"), where="source is not null"),
    Mapping("nChars", "documents", _DOC, "cast(n_chars as string)", "int", "n_chars is not null"),
    Mapping("quality", "labels", _DOC, _entity("quality", "quality"), where="quality is not null"),
    Mapping("toxic", "labels", _DOC, _entity("toxic", "toxic"), where="toxic is not null"),
    Mapping("url", "pages", _PAGE, "url", "str", "url is not null"),
    Mapping("text", "benchmark", _ITEM, "text", "str", "text is not null"),
    Mapping("hasLabel", "embeddings", _VEC, _entity("label", "label"), where="label is not null"),
)
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "benchmark", "labels", "conversations", "embeddings")
#: Tables with a unique key behind their mappings.
UNIQUE = frozenset({"region", "nation", "customer", "supplier", "part", "orders", "events", "pages", "benchmark", "conversations", "embeddings"})
PREDICATES = tuple(dict.fromkeys(m.predicate for m in MAPPINGS))
#: Predicates of names, places, dealings and orders: what most workloads touch.
CORE = tuple(p for p in PREDICATES if p not in ("url", "text"))


def predicate_sql(predicate: str) -> str:
    """The predicate's distinct (s, o) as SQL over the relational tables."""
    return " union ".join(m.sql for m in MAPPINGS if m.predicate == predicate)


def triples_sql(predicates: tuple[str, ...] = PREDICATES) -> str:
    """All triples (s, p, o) as SQL over the relational tables."""
    return " union all ".join(f"select s, '{p}' as p, o from ({predicate_sql(p)}) as t_{p}" for p in predicates)


def register_tables(spark: SparkSession, sf_dir: str, suffix: str) -> dict[str, str]:
    """Temporary views of the tables, by names that sessions don't share."""
    names = {}
    for t in TABLES:
        names[t] = f"{t}__{suffix}"
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(names[t])
    return names


def triples_from_tables(spark: SparkSession, sf_dir: str, predicates: tuple[str, ...] = PREDICATES) -> DataFrame:
    """(s, p, o, o_kind, o_num): the set of triples of the tables; o_num is the number of numeric objects.

    Predicates with a unique key behind them aren't deduplicated; only lineitem, whose key repeats,
    and derived tables are, which costs a shuffle of these predicates alone.
    """
    parts = []
    for m in MAPPINGS:
        if m.predicate not in predicates:
            continue
        source = _source(spark, sf_dir, m.table)
        rows = source.where(m.where) if m.where else source
        rows = rows.selectExpr(f"{m.subject} as s", f"'{m.predicate}' as p", f"{m.object} as o").where("s is not null and o is not null")
        rows = rows if m.table in UNIQUE else rows.distinct()
        number = F.col("o").cast("double") if m.kind in ("int", "dec") else F.lit(None).cast("double")
        parts.append(rows.withColumn("o_kind", F.lit(m.kind)).withColumn("o_num", number))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _source(spark: SparkSession, sf_dir: str, table: str, distinct: bool = True) -> DataFrame:
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    if table == _SOLD:
        sold = read("lineitem").join(read("orders"), F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_partkey", "l_suppkey")
        return sold.distinct() if distinct else sold
    if table == _NEXT:
        from pyspark.sql import Window

        later = F.min("turn").over(Window.partitionBy("conv_id").orderBy("turn").rangeBetween(1, Window.unboundedFollowing))
        return read("conversations").select("conv_id", "turn", later.alias("later")).where("later is not null")
    return read(table)


def placed_mapping(spark: SparkSession, sf_dir: str, m: Mapping, workers: int) -> DataFrame:
    """(home, s, o) of one mapping, dealt by the subject's home: raw columns travel, names are made at the home.

    All rows of a subject meet there, so that what isn't unique is made distinct without another shuffle.
    """
    from .store import home

    source = _source(spark, sf_dir, m.table, distinct=False)
    rows = source.where(m.where) if m.where else source
    rows = rows.where(f"({m.subject}) is not null and ({m.object}) is not null")
    used = [c for c in source.columns if re.search(rf"\b{re.escape(c)}\b", f"{m.subject} {m.object}")]
    dealt = rows.select(home(F.expr(m.subject), workers).alias("home"), *used).repartition(workers, "home")
    named = dealt.selectExpr("home", f"{m.subject} as s", f"{m.object} as o")
    return named if m.table in UNIQUE else named.dropDuplicates(["home", "s", "o"])


def mapped(spark: SparkSession, sf_dir: str, m: Mapping) -> DataFrame:
    """(s, o) of one mapping where it lies; rows of a table without a key may repeat."""
    source = _source(spark, sf_dir, m.table, distinct=False)
    rows = source.where(m.where) if m.where else source
    return rows.selectExpr(f"{m.subject} as s", f"{m.object} as o").where("s is not null and o is not null")


@dataclass(frozen=True)
class Star:
    """Rows of a table that give one subject several objects; (s, o) of all that is not null, as often as rows have it."""

    source: DataFrame
    subject: str
    objects: tuple[str, ...]


#: Kinds of objects that hold no slash, and so are no subject's name.
NUMBERS = ("int", "dec", "date")


def prefix_of(term: str) -> str:
    """What all names made by a mapping's expression begin with; empty if nothing is known."""
    found = re.match(r"(?:concat\()?'([^']*)'", term)
    return found[1] if found else ""


def star_groups(mappings: Iterable[Mapping]) -> dict[tuple[str, str], list[Mapping]]:
    """Mappings of one table and subject together."""
    groups: dict[tuple[str, str], list[Mapping]] = {}
    for m in mappings:
        groups.setdefault((m.table, m.subject), []).append(m)
    return groups


def stars_of(spark: SparkSession, sf_dir: str, mappings: Iterable[Mapping]) -> list[Star]:
    """The rows of `mapped` of all mappings, those of one table and subject together."""
    return [Star(_source(spark, sf_dir, table, distinct=False), subject, tuple(f"case when {m.where} then {m.object} end" if m.where else m.object for m in ms)) for (table, subject), ms in star_groups(mappings).items()]


def typed_object(kind: str, column: str = "o"):
    """The object as a value of its kind; null where it doesn't read as one."""
    kinds = {"int": "bigint", "dec": "double", "dbl": "double", "date": "date", "ts": "timestamp"}
    return F.expr(f"try_cast({column} as {kinds[kind]})") if kind in kinds else F.col(column)
