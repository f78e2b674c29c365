"""Incremental redistribution, the indexes over what it made, and answering from them without exchange."""

from __future__ import annotations

import uuid
import weakref
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.evaluate import by_worker, local_join
from ..plans.patterns import Const, Pattern, Term, Var
from ..session import shared_folder
from ..sources.store import Store, home, seeds
from .tree import Edge, Path, Tree, residual_equalities


@dataclass
class Module:
    """Storage of one pattern-index edge: the main store's predicate, or a replicated table."""

    path: Path
    constant: str | None  # child constant that it is restricted to
    table: str | None  # None: the core is the subject, so the main store has it in place
    triples: int = 0
    folder: str = ""
    used: int = 0
    touched: int = 0
    sent: int = 0  # values that making it has sent between workers
    readers: int = 0  # answers handed out that read its table, and are still held


@dataclass
class Index:
    """Pattern index (paths, constants, times) and replica index (tables) under a budget of triples.

    An evicted module leaves the index at once. Its files go when the last answer that reads them
    is let go: who holds an answer can still run it, and what is derived from it.
    """

    store: Store
    modules: dict[Path, Module] = field(default_factory=dict)
    clock: int = 0
    moved: int = 0  # triples that redistribution has read and written so far
    evicted: int = 0
    sent: int = 0  # values that redistribution has sent between workers so far
    retired: list[Module] = field(default_factory=list)  # dropped, but still read by answers

    @property
    def replicas(self) -> int:
        return sum(m.triples for m in self.modules.values())

    def lease(self, answer: DataFrame, tree: Tree) -> DataFrame:
        """Keeps the files of a covered query's modules for as long as its answer is held."""
        held = [m for m in {p: self.modules[p] for p in tree.paths}.values() if m.table]

        def release() -> None:
            for m in held:
                m.readers -= 1

        for m in held:
            m.readers += 1
        weakref.finalize(answer, release).atexit = False
        return answer

    def sweep(self) -> None:
        """Deletes the files of retired modules that no answer reads any more."""
        for m in [m for m in self.retired if m.readers <= 0]:
            self.retired.remove(m)
            spark = self.store.spark
            spark.sql(f"drop table if exists {m.table}")
            where = spark._jvm.org.apache.hadoop.fs.Path(m.folder)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)

    def covers(self, tree: Tree) -> bool:
        """All edges are here, and none is restricted to a constant that the query doesn't have there."""
        for e in tree.edges:
            m = self.modules.get(e.path)
            if m is None:
                return False
            v = tree.vertices[e.child]
            # along the whole path: a parent's restriction has restricted this module too
            if m.constant is not None and not (isinstance(v, Const) and v.value == m.constant):
                return False
        return True

    def touch(self, tree: Tree) -> None:
        self.clock += 1
        for path in tree.paths:
            self.modules[path].used = self.clock

    def rows(self, path: Path) -> DataFrame:
        """(home, s, o) of a module."""
        m = self.modules[path]
        predicate = path[-1][0]
        if m.table is None:
            rows = self.store.scan(Pattern(Var("s"), Const(predicate), Const(m.constant) if m.constant else Var("o")), ("s", "o"))
            return rows
        return self.store.spark.table(m.table)

    def add(self, path: Path, constant: str | None = None) -> Module:
        """Makes the module of a path whose parent is there: one job, appended, deduplicated by home."""
        if path in self.modules:
            return self.modules[path]
        predicate, out = path[-1]
        self.clock += 1
        child = Const(constant) if constant else Var("c")
        source = self.store.scan(Pattern(Var("v"), Const(predicate), child) if out else Pattern(child, Const(predicate), Var("v")), ("s", "o"))
        if len(path) == 1:
            if out:
                self.modules[path] = Module(path, constant, None, used=self.clock)
                return self.modules[path]
            placed, keys = source.select(home("o", self.store.workers).alias("home"), "s", "o"), None
        else:
            parent_predicate, parent_out = path[-2]
            parents = self.rows(path[:-1]).select("home", F.col("o" if parent_out else "s").alias("v")).distinct()
            placed = parents.join(source.drop("home"), F.col("v") == F.col("s" if out else "o")).select("home", "s", "o").distinct()
            keys = parents
        tag = uuid.uuid4().hex[:12]
        name, folder = f"trellis_module_{tag}", f"{shared_folder(self.store.spark)}/module-{tag}"
        by = "s" if out else "o"
        placed.repartition(self.store.workers, "home").sortWithinPartitions("home", by).write.bucketBy(self.store.workers, "home").sortBy(by).option("path", folder).saveAsTable(name)
        away = lambda c: F.count_if(F.col("home") != home(c, self.store.workers)).alias("away")
        made = self.store.spark.table(name).agg(F.count("*").alias("n"), away("s")).first()
        asked = keys.agg(away("v")).first()["away"] if keys is not None and out else keys.count() * (self.store.workers - 1) if keys is not None else 0
        known = self.store.stats.get(predicate)
        # keys that ask at another home (of subjects; else at all), and two values for each triple that comes from one
        self.modules[path] = Module(path, constant, name, made["n"], folder, self.clock, touched=made["n"] + (known.card if known else 0), sent=asked + 2 * made["away"])
        self.moved += self.modules[path].touched
        self.sent += self.modules[path].sent
        return self.modules[path]

    def redistribute(self, hot: dict[Path, str | None]) -> list[Path]:
        """Modules of hot paths, parents first; a path shared by several patterns is made once."""
        made = []
        for path, constant in sorted(hot.items(), key=lambda x: len(x[0])):
            if path not in self.modules and (len(path) == 1 or path[:-1] in self.modules):
                self.add(path, constant)
                made.append(path)
        return made

    def evict(self, budget: float) -> list[Path]:
        """Drops least recently used leaf modules until replicas fit the budget; a parent outlives its children."""
        gone = []
        while self.replicas > budget:
            leaves = [m for p, m in self.modules.items() if not any(q != p and q[: len(p)] == p for q in self.modules)]
            m = min(leaves, key=lambda m: (m.used, -len(m.path)))
            self.drop(m.path)
            gone.append(m.path)
            self.evicted += 1
        return gone

    def drop(self, path: Path) -> None:
        m = self.modules.pop(path)
        if m.table:
            self.retired.append(m)
        self.sweep()

    def prove_empty(self, tree: Tree) -> bool:
        """Whether a module of the query has no triple at all: the answer is known before anything runs."""
        return any((m.triples == 0) if m.table else self.store.stats.get(p[-1][0]) is None for p in tree.paths for m in [self.modules[p]])


def edge_order(index: Index, tree: Tree, size: Callable[[Edge], float]) -> tuple[Edge, ...]:
    """Constants first, then the smallest modules; parents before children."""
    left, have, out = list(tree.edges), {0}, []
    while left:
        e = min((e for e in left if e.parent in have), key=lambda e: (not isinstance(tree.vertices[e.child], Const), size(e)))
        left.remove(e)
        have.add(e.child)
        out.append(e)
    return tuple(out)


def parallel(index: Index, tree: Tree, order: tuple[Edge, ...] | None = None, homes: list[int] | None = None) -> DataFrame:
    """(home, variables) of a covered query: each worker joins its own modules; nothing moves.

    A vertex of the tree is a column; copies of one query vertex are compared at the end. The core
    has one home for each value, so no answer comes twice and none is made distinct.
    """
    store, out = index.store, None
    merged = lambda e: index.modules[e.path].triples or getattr(store.stats.get(e.predicate), "card", 0)
    for e in order or edge_order(index, tree, merged):
        rows = index.rows(e.path)
        rows = rows.select("home", F.col("s" if e.out else "o").alias(f"v{e.parent}"), F.col("o" if e.out else "s").alias(f"v{e.child}"))
        rows = rows.where(F.col("home").isin(homes)) if homes is not None else rows
        v = tree.vertices[e.child]
        if isinstance(v, Const):
            rows = rows.where(F.col(f"v{e.child}") == store.value(v))
        if isinstance(tree.root, Const) and e.parent == 0:
            rows = rows.where((F.col("home") == store.home_of(tree.root)) & (F.col("v0") == store.value(tree.root)))
        out = rows if out is None else local_join(out, rows)
    for a, b in residual_equalities(tree):
        out = out.where(F.col(f"v{a}") == F.col(f"v{b}"))
    first: dict[Term, int] = {}
    for k, v in enumerate(tree.vertices):
        first.setdefault(v, k)
    return out.select("home", *[F.col(f"v{k}").alias(v.name) for v, k in first.items() if isinstance(v, Var)])


def parallel_by_worker(index: Index, tree: Tree) -> DataFrame:
    """The same, each worker in the order of the sizes that the modules have at its own home."""
    every = reduce(DataFrame.union, [index.rows(e.path).groupBy("home").agg(F.count("*").alias("n")).withColumn("k", F.lit(k)) for k, e in enumerate(tree.edges)])
    sizes = {(r["home"], r["k"]): r["n"] for r in every.collect()}  # workers x edges
    number = {e: k for k, e in enumerate(tree.edges)}
    orders = {w: edge_order(index, tree, lambda e, w=w: sizes.get((w, number[e]), 0)) for w in seeds(index.store.workers)}
    return index.lease(by_worker(index.store, orders, lambda order, homes: parallel(index, tree, order, homes)), tree)
