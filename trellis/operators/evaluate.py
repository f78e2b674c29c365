"""Distributed evaluation: rows stay at the home of the first pattern's subject, keys and candidates move."""

from __future__ import annotations

import weakref
from collections import deque
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.cost import Case, Knowledge, Plan, order_locally, plan_order
from ..plans.patterns import BGP, Const, Pattern, Term, Var, components, is_subject_star
from ..session import checkpointed
from ..plans.stats import Predicate
from ..sources.store import Store, home, seeds

#: Bytes up to which keys are sent to all homes: their number is bounded by exact statistics.
BROADCAST_BYTES = 64 << 20
#: Assumed bytes of a key row.
KEY_BYTES = 64
#: Joins after which the lineage is cut.
CUT_AFTER = 8


@dataclass
class Traffic:
    """What joins would move between workers: counted, on request, from the keys and candidates themselves."""

    keys: int = 0
    values: int = 0
    steps: list[tuple[str, str, int, int]] = field(default_factory=list)

    @property
    def total(self) -> int:
        return self.keys + self.values


@dataclass(frozen=True)
class Options:
    locality: bool = True  # use that subjects are hashed; else every join sends keys to all homes
    pinning: bool = True  # use that rows stay at their pinned subject
    broadcast_bytes: int = BROADCAST_BYTES
    prune: bool = True
    seed: str = "max_out"
    reduce: bool = True  # semi-joins; else candidates are whole predicates
    fuse: bool = True  # keys that go to the same homes for several patterns in a row are sent once


def on_shared(left: DataFrame, right: DataFrame, names: list[str], how: str = "inner") -> DataFrame:
    """Join on home and the named columns, which are compared with their own kinds of null."""
    return left.join(right.hint("merge"), ["home", *names], how)  # placed by home already: merging needs no exchange


def local_join(left: DataFrame, right: DataFrame) -> DataFrame:
    """Every worker joins what it has: no exchange where both sides lie by home."""
    return on_shared(left, right, [c for c in left.columns if c in right.columns and c != "home"])


def keys_of(left: DataFrame, column: str) -> DataFrame:
    """(origin, key): the distinct keys of each home."""
    return left.select(F.col("home").alias("origin"), F.col(column).alias("__key")).distinct()


def semi_join(store: Store, left: DataFrame, patterns: tuple[Pattern, ...], column: str, route: str, most: int | None, options: Options, traffic: Traffic | None = None) -> DataFrame:
    """Joins a pattern by sending keys out and candidates back; `left` itself doesn't move.

    Several patterns, of which the key is the subject, are joined at its home before they answer.

    hash: a key goes to the home of the subject it is. broadcast: a key goes to all homes, if the
    bound on the number of keys, from exact statistics, allows; else keys and the predicate meet
    by the column's hash, which returns the same candidates.
    """
    right = reduce(local_join, [store.answer(p) for p in patterns])
    keys = keys_of(left, column)
    if route == "hash":
        sent = keys.withColumn("home", home("__key", store.workers))
        met = sent.join(right.withColumnRenamed(column, "__value"), (sent["home"] == right["home"]) & (F.col("__key") == F.col("__value")))
        candidates = met.select(F.col("origin"), sent["home"].alias("at"), F.col("__key").alias(column), *[c for c in right.columns if c not in ("home", column)])
    else:
        if most is not None and most * store.workers * KEY_BYTES <= options.broadcast_bytes:
            keys = F.broadcast(keys)
        met = right.withColumnRenamed("home", "at").join(keys, F.col(column) == F.col("__key"))
        candidates = met.select("origin", "at", *[c for c in right.columns if c != "home"])
    if traffic is not None:
        meter(store, keys, candidates, patterns, column, route, traffic)
    back = candidates.drop("at").withColumnRenamed("origin", "home")
    return on_shared(left, back, [c for c in left.columns if c in back.columns and c != "home"])


def meter(store: Store, keys: DataFrame, candidates: DataFrame, patterns: tuple[Pattern, ...], column: str, route: str, traffic: Traffic) -> None:
    """Keys sent to another home and values of candidates that come back from one; what stays costs nothing."""
    width = len({v for p in patterns for v in p.variables})
    if route == "hash":
        sent = keys.where(home("__key", store.workers) != F.col("origin")).count()
    else:
        sent = keys.count() * (store.workers - 1)
    returned = candidates.where("origin != at").count() * width
    traffic.keys += sent
    traffic.values += returned
    traffic.steps.append((" . ".join(map(str, patterns)), route, sent, returned))


def bound_of(done: list[tuple[Pattern, object]], column: str) -> int | None:
    """A proven bound on the distinct values of a column: the least distinct count of the patterns that bind it."""
    bounds = [k.n_s if "s" in p.slots(column) else k.n_o for p, k in done if p.slots(column) and set(p.slots(column)) & set("so")]
    return min(bounds, default=None)


def fused(plan: Plan, options: Options) -> list[tuple[tuple[Pattern, ...], Case | None, str | None]]:
    """The plan's steps; patterns in a row that hash-routed keys of one column ask for are one step."""
    out: list[tuple[tuple[Pattern, ...], Case | None, str | None]] = []
    for p, case, column in plan.steps:
        if options.fuse and out and case is Case.HASH and out[-1][1:] == (case, column):
            out[-1] = ((*out[-1][0], p), case, column)
        else:
            out.append(((p,), case, column))
    return out


def execute(store: Store, plan: Plan, options: Options | None = None, traffic: Traffic | None = None, known: Knowledge | None = None) -> DataFrame:
    """(home, variables) of a connected pattern, joined in the plan's order."""
    options, known = options or Options(), known or store.knowledge
    give_back()
    out: DataFrame | None = None
    done: list[tuple[Pattern, object]] = []
    kept: list[DataFrame] = []
    moved = False  # a semi-join is in `out`: it is kept before the next, which reads it twice
    cut = CUT_AFTER
    for together, case, column in fused(plan, options):
        p = together[0]
        if out is None:
            out = store.answer(p)
        elif case is Case.LOCAL:
            out = local_join(out, store.answer(p))
        else:
            if moved:
                out = out.persist(StorageLevel.DISK_ONLY)
                kept.append(out)
            out = semi_join(store, out, together, column, "hash" if case is Case.HASH else "broadcast", bound_of(done, column), options, traffic)
            moved = True
        done += [(q, known(q)) for q in together]
        if len(done) > cut:
            cut += CUT_AFTER
            out = checkpointed(out).repartition(store.workers, "home")
            moved = False
    return with_kept(out, kept)


#: Steps of answers that were let go; a finalizer may run in the middle of a call to the JVM, so blocks are given back later.
_LET_GO: deque[DataFrame] = deque()


def give_back() -> None:
    """Frees the blocks of steps that no answer needs any more."""
    while _LET_GO:
        _LET_GO.popleft().unpersist()


def with_kept(out: DataFrame, kept: list[DataFrame]) -> DataFrame:
    """An answer whose steps' blocks are freed, with the next query, once it is let go; what is derived from it then recomputes them."""
    for step in kept:
        weakref.finalize(out, _LET_GO.append, step).atexit = False
    return out


def connected(bgp: BGP, cross: bool = False) -> None:
    if len(components(bgp)) > 1 and not cross:
        raise ValueError("the pattern isn't connected; ask for the product of its parts explicitly")


def distributed(store: Store, bgp: BGP, options: Options | None = None, traffic: Traffic | None = None, cross: bool = False) -> DataFrame:
    """Answers of a pattern by the planner's order; unconnected parts only on demand."""
    options = options or Options()
    parts = components(bgp)
    connected(bgp, cross)
    store.refine_all(bgp)
    outs = []
    for part in parts:
        plan = plan_order(part, store.knowledge, store.workers, options.locality, options.pinning, options.prune, options.seed)
        outs.append(execute(store, plan, options, traffic))
    return reduce(lambda a, b: a.drop("home").crossJoin(b.drop("home")).withColumn("home", F.lit(0)), outs)


def star(store: Store, bgp: BGP) -> DataFrame:
    """A star around one subject: local joins of bucketed scans, without any exchange."""
    if not is_subject_star(bgp):
        raise ValueError("not a star around one subject")
    store.refine_all(bgp)
    order = order_locally(bgp, store.knowledge)
    return reduce(local_join, [store.answer(p) for p in order])


def by_worker(store: Store, orders: dict[int, tuple], run: Callable[[tuple, list[int]], DataFrame]) -> DataFrame:
    """Plans of workers that chose the same order as one, on their own buckets; the union of these."""
    groups: dict[tuple, list[int]] = {}
    for worker, order in orders.items():
        groups.setdefault(order, []).append(worker)
    return reduce(DataFrame.union, [run(order, homes) for order, homes in groups.items()])


def star_by_worker(store: Store, bgp: BGP) -> DataFrame:
    """A star in which each worker joins in the order of its own statistics."""
    if not is_subject_star(bgp):
        raise ValueError("not a star around one subject")
    store.refine_all(bgp)

    def own(worker: int) -> Knowledge:
        def known(p: Pattern) -> Predicate:
            whole, base = store.knowledge(p), store.counts(str(p.p))
            here = store.local_statistics(map(str, (q.p for q in bgp)))[worker].get(str(p.p))
            if base is None:
                return whole
            if here is None:
                return Predicate(str(p.p), 0, 0, 0)
            share = whole.card / base.card if base.card else 0.0  # of constants, which only the whole knows
            return Predicate(str(p.p), round(here.card * share), max(1, round(here.n_s * share)), max(1, round(here.n_o * share)))

        return known

    orders = {w: tuple(order_locally(bgp, own(w))) for w in seeds(store.workers)}
    names = ["home", *bgp.variables]
    return by_worker(store, orders, lambda order, homes: reduce(local_join, [store.answer(p).where(F.col("home").isin(homes)) for p in order]).select(*names))


def plain(triples: Callable[[Pattern], DataFrame], bgp: BGP, hint: str | None = None, cross: bool = False) -> DataFrame:
    """The reference: joins of pattern scans in text order, connected ones first, as Catalyst likes them."""
    connected(bgp, cross)
    left, out, have = list(bgp.patterns), None, set()
    while left:
        p = next((p for p in left if have & set(p.variables)), left[0])
        left.remove(p)
        right = triples(p)
        if out is None:
            out = right
        else:
            shared = [v for v in p.variables if v in have]
            right = right.hint(hint) if hint else right
            out = out.join(right, shared) if shared else out.crossJoin(right)
        have |= set(p.variables)
    return out


def plain_of(store: Store, bgp: BGP, hint: str | None = None) -> DataFrame:
    return plain(lambda p: store.answer(p).drop("home"), bgp, hint)


def bound_term(t: Term, columns: dict[str, Column]) -> Column | None:
    return columns.get(t.name) if isinstance(t, Var) else None


def projected(answers: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """Named columns in order; variables that nothing binds are null."""
    return answers.select(*[F.col(n) if n in answers.columns else F.lit(None).cast("string").alias(n) for n in names])


def exchanges(df: DataFrame) -> int:
    """Shuffles and broadcasts of rows in the plan that would run."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return text.count("Exchange hashpartitioning") + text.count("Exchange rangepartitioning") + text.count("Exchange RoundRobin") + text.count("BroadcastExchange") + text.count("Exchange SinglePartition")


def constant_at(p: Pattern) -> list[Const]:
    return [t for t in (p.s, p.p, p.o) if isinstance(t, Const)]
