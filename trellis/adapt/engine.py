"""The controller: plans, runs, watches, detects, redistributes, evicts, and can be restored from its log."""

from __future__ import annotations

import time
from collections.abc import Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.evaluate import Options, Traffic, distributed, projected, star
from ..plans.cost import plan_order
from ..plans.parser import parse
from ..plans.patterns import BGP, Query, Var, components, is_subject_star, query_text
from ..plans.stats import Predicate
from ..sources.store import Store
from .heatmap import HeatMap
from .redistribute import Index, parallel
from .tree import Tree, build_tree, vertex_scores


#: Values that a core vertex has for each worker at least.
LEAST_FOR_EACH = 4


@dataclass
class Run:
    """What became of one query."""

    text: str
    mode: str
    seconds: float = 0.0
    traffic: int = 0
    sent: int = 0  # values that redistribution after it has sent between workers
    replicas: int = 0
    made: int = 0
    evicted: int = 0
    rows: int | None = None


@dataclass
class Engine:
    store: Store
    adaptive: bool = True
    threshold: int = 10
    budget: float = 0.2  # replicas as a share of the triples
    policy: str = "high_low"
    options: Options = field(default_factory=Options)
    guard: bool = True  # pass over cores that have fewer values than there are workers
    frozen: bool = False
    heat: HeatMap = field(default_factory=HeatMap)
    log: list[Run] = field(default_factory=list)
    saved: int = 0  # entries of the log that are stored already
    index: Index = field(init=False)

    def __post_init__(self):
        self.index = Index(self.store)

    # --- planning

    def rule(self) -> dict:
        """How trees are grown, as `build_tree` takes it: the same for the engine's own queries and for a monitored stream."""
        return {"policy": self.policy, "stats": self.store.raw_stats, "least": LEAST_FOR_EACH * self.store.workers if self.guard else 0}

    def tree(self, bgp: BGP) -> Tree | None:
        """The query's tree under this version's scores; None where it has none."""
        if any(isinstance(p.p, Var) for p in bgp) or len(components(bgp)) > 1:
            return None
        try:
            return build_tree(bgp, vertex_scores(bgp, self.store.stats, self.policy), **self.rule())
        except ValueError:
            return None

    def mode(self, bgp: BGP) -> tuple[str, Tree | None]:
        if is_subject_star(bgp):
            return "star", self.tree(bgp) if self.adaptive else None
        tree = self.tree(bgp) if self.adaptive else None
        return ("parallel" if tree is not None and self.index.covers(tree) else "distributed"), tree

    def explain(self, query: str | Query | BGP) -> dict:
        bgp = self._query(query).bgp
        mode, tree = self.mode(bgp)
        out = {"mode": mode, "core": str(tree.root) if tree else None}
        if mode == "distributed":
            self.store.refine_all(bgp)
            plan = plan_order(bgp, self.store.knowledge, self.store.workers, self.options.locality, self.options.pinning)
            out |= {"cost": plan.state.cost, "joins": [(str(p), c.value if c else "scan", v) for p, c, v in plan.steps]}
        out["physical"] = self.answer(bgp)[0]._jdf.queryExecution().executedPlan().toString()
        return out

    # --- running

    @staticmethod
    def _query(query: str | Query | BGP) -> Query:
        return parse(query) if isinstance(query, str) else Query(query) if isinstance(query, BGP) else query

    def answer(self, bgp: BGP, traffic: Traffic | None = None) -> tuple[DataFrame, str]:
        """Bindings of a pattern, in the cheapest mode that the index allows now."""
        mode, tree = self.mode(bgp)
        if mode == "star":
            return star(self.store, bgp), mode
        if mode == "parallel":
            self.index.touch(tree)
            out = parallel(self.index, tree)
            if self.index.prove_empty(tree):
                return self.index.lease(out.limit(0), tree), "empty"
            return self.index.lease(out, tree), mode
        return distributed(self.store, bgp, self.options, traffic), mode

    def run(self, query: str | Query | BGP, meter: bool = False, count: bool = False, sink: bool = False) -> DataFrame:
        """The answer; the query is observed, and what got hot is redistributed after it.

        With `sink`, all rows are made first, and thrown away.
        """
        q = self._query(query)
        began = time.perf_counter()
        traffic = Traffic() if meter else None
        bindings, mode = self.answer(q.bgp, traffic)
        out = self.finish(q, bindings)
        if mode in ("parallel", "empty"):
            self.index.lease(out, self.mode(q.bgp)[1])
        rows = out.count() if count else None
        if sink:
            out.write.format("noop").mode("overwrite").save()
        run = Run(query if isinstance(query, str) else query_text(q.bgp), mode, time.perf_counter() - began, traffic.total if traffic else 0, rows=rows)
        if self.adaptive and not self.frozen:
            before, sent = self.index.evicted, self.index.sent
            run.made = len(self.observe(q.bgp))
            run.evicted, run.sent = self.index.evicted - before, self.index.sent - sent
        run.replicas = self.index.replicas
        self.log.append(run)
        return out

    def finish(self, q: Query, bindings: DataFrame) -> DataFrame:
        """Optional parts, filters, projection and modifiers around the pattern's bindings."""
        out = self.store.decode(bindings).drop("home")
        for part in q.optional:
            right = self.store.decode(distributed(self.store, part, self.options)).drop("home")
            out = out.join(right, [c for c in right.columns if c in out.columns], "left")
        for f in q.filters:
            out = out.where(f)
        if q.ask:
            return out.limit(1).agg((F.count("*") > 0).alias("answer"))
        sorts = [F.col(v).desc() if down else F.col(v).asc() for v, down in q.order_by]
        if q.distinct:
            out = projected(out, q.projection).distinct()
            out = out.orderBy(*sorts) if sorts else out
        else:
            out = projected(out.orderBy(*sorts) if sorts else out, q.projection)
        out = out.offset(q.offset) if q.offset else out
        return out.limit(q.limit) if q.limit is not None else out

    # --- adapting

    def observe(self, bgp: BGP) -> list:
        tree = self.tree(bgp)
        if tree is None:
            return []
        self.heat.add(tree)
        return self.adapt()

    def adapt(self) -> list:
        hot = self.heat.hot(self.threshold)
        for path, m in list(self.index.modules.items()):  # a constant that no longer dominates holds queries back
            if path in self.index.modules and m.constant is not None and path in hot and hot[path] != m.constant:
                for below in [p for p in self.index.modules if p[: len(path)] == path]:
                    self.index.drop(below)
        made = self.index.redistribute(hot)
        if made:
            self.index.evict(self.budget * self.store.total)
        return made

    def train(self, queries: Iterable[str | Query | BGP]) -> Engine:
        """Shows a workload to the heat map only, then redistributes what is hot in it."""
        for q in queries:
            if (tree := self.tree(self._query(q).bgp)) is not None:
                self.heat.add(tree)
        self.adapt()
        return self

    def freeze(self) -> Engine:
        self.frozen = True
        return self

    def save(self, path: str) -> str:
        """Appends what the log has gained since the last time, as JSON lines: (k, text)."""
        new = [(k, r.text) for k, r in enumerate(self.log) if k >= self.saved]
        if new:
            self.store.spark.createDataFrame(new, "k long, text string").coalesce(1).write.mode("append").json(path)
            self.saved = len(self.log)
        return path

    def restore(self, path: str) -> Engine:
        """A new engine, its heat map and indexes replayed from a stored log; the store is read as it is."""
        rows = self.store.spark.read.schema("k long, text string").json(path).orderBy("k")
        out = replace(self, heat=HeatMap(), log=[], frozen=False, saved=0)
        for r in rows.toLocalIterator():
            if (tree := out.tree(parse(r["text"]).bgp)) is not None:
                out.heat.add(tree)
        out.adapt()
        return out

    def restored(self, queries: Iterable[str | Query | BGP]) -> Engine:
        """A new engine over the same store with this one's settings, its state replayed from a query log."""
        return replace(self, heat=HeatMap(), log=[], frozen=False).train(queries)

    def statistics(self) -> dict[str, Predicate]:
        return self.store.stats
