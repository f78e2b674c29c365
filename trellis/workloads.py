"""The experiment workloads on the given tables: templates, their oracles in plain SQL, and generators."""

from __future__ import annotations

import random
from dataclasses import dataclass
from itertools import combinations

from .plans.patterns import BGP, Const, Pattern, Var, components, query_text
from .sources.vocab import predicate_sql, triples_sql

# Patterns by name; blank-separated terms, ` . ` between patterns.
TEMPLATES: dict[str, str] = {
    # university-like queries
    "uni_q01": "?x type class/Customer . ?x bought part/1",
    "uni_q02": "?x type class/Customer . ?y type class/Nation . ?z type class/Supplier . ?x boughtFrom ?z . ?z basedIn ?y . ?x locatedIn ?y",
    "uni_q03": "?x type class/Order . ?x placedBy customer/1",
    "uni_q04": "?x type class/Customer . ?x locatedIn nation/1 . ?x label ?a . ?x balance ?b . ?x segment ?c",
    "uni_q05": "?x type class/Customer . ?x locatedIn nation/1",
    "uni_q06": "?x type class/Part",
    "uni_q07": "?x type class/Customer . ?y type class/Part . ?x bought ?y . supplier/1 supplies ?y",
    "uni_q08": "?x type class/Customer . ?y type class/Nation . ?x locatedIn ?y . ?y partOf region/1 . ?x label ?z",
    "uni_q09": "?x type class/Customer . ?y type class/Supplier . ?z type class/Part . ?x boughtFrom ?y . ?y supplies ?z . ?x bought ?z",
    "uni_q10": "?x segment segment/BUILDING . ?x bought part/1",
    "uni_q11": "?x type class/Supplier . ?x basedIn ?z . ?z partOf region/1",
    "uni_q12": "?y type class/Nation . ?x basedIn ?y . ?y partOf region/1",
    "uni_q13": "?x type class/Customer . ?x boughtFrom supplier/1",
    "uni_q14": "?x type class/Customer",
    # the seven of the runtime comparison: two cycles of large results, one star, one cycle that is empty at a join, selective stars
    "uni_l1": "?x type class/Customer . ?y type class/Nation . ?z type class/Supplier . ?x boughtFrom ?z . ?z basedIn ?y . ?x locatedIn ?y",
    "uni_l2": "?x type class/Line . ?x ofPart ?y",
    "uni_l3": "?y type class/Supplier . ?y locatedIn ?x . ?x type class/Nation . ?y boughtFrom ?s . ?s basedIn ?x",
    "uni_l4": "?x type class/Customer . ?x locatedIn nation/1 . ?x label ?a . ?x balance ?b . ?x segment ?c",
    "uni_l5": "?x type class/Customer . ?x locatedIn nation/1",
    "uni_l6": "?x type class/Supplier . ?x basedIn ?z . ?z partOf region/1",
    "uni_l7": "?x type class/Customer . ?y type class/Supplier . ?z type class/Part . ?x boughtFrom ?y . ?y supplies ?z . ?x bought ?z",
    # linear
    "div_l1": "?i inOrder ?o . ?o placedBy customer/1",
    "div_l2": "?e byUser ?c . ?c locatedIn nation/1",
    "div_l3": "customer/1 boughtFrom ?s . ?s basedIn ?n",
    "div_l4": "turn/0-0 nextTurn ?t . ?t role ?r",
    "div_l5": "supplier/1 supplies ?p . ?p brand ?b",
    # star
    "div_s1": "?c type class/Customer . ?c segment segment/BUILDING . ?c locatedIn ?n . ?c label ?l . ?c balance ?b",
    "div_s2": "?o status status/F . ?o priority ?r . ?o orderDate ?d . ?o placedBy ?c",
    "div_s3": "?i returnFlag flag/R . ?i ofPart part/1 . ?i fromSupplier ?s . ?i inOrder ?o",
    "div_s4": "?p brand brand/Brand#1 . ?p size 12 . ?p category ?k . ?p label ?l",
    "div_s5": "?s basedIn nation/1 . ?s label ?l . ?s balance ?b",
    "div_s6": "?e kind kind/purchase . ?e byUser customer/1",
    "div_s7": "?d lang lang/en . ?d source ?s . ?d quality quality/1 . ?d toxic ?x",
    # snowflake
    "div_f1": "?i returnFlag flag/R . ?i ofPart ?p . ?i inOrder ?o . ?o status ?st . ?o placedBy customer/1 . ?o priority ?r",
    "div_f2": "?o priority priority/1-URGENT . ?o status ?st . ?o placedBy ?c . ?c segment ?g . ?c locatedIn nation/1 . ?c label ?l",
    "div_f3": "?i fromSupplier ?s . ?i inOrder ?o . ?i ofPart ?p . ?p brand brand/Brand#1 . ?p size 12 . ?p label ?l",
    "div_f4": "?e kind kind/error . ?e byUser ?c . ?c segment segment/BUILDING . ?c locatedIn ?n . ?n partOf ?r",
    "div_f5": "?i returnFlag ?f . ?i ofPart ?p . ?i fromSupplier ?s . ?s basedIn nation/1 . ?s label ?l . ?s balance ?b",
    # complex
    "div_c1": "?c boughtFrom ?s . ?s supplies ?p . ?c bought ?p . ?p brand brand/Brand#1 . ?p size 12",
    "div_c2": "?c1 locatedIn ?n . ?c2 locatedIn ?n . ?c1 bought ?p . ?c2 bought ?p . ?p brand brand/Brand#1 . ?n partOf region/1",
    "div_c3": "?i inOrder ?o . ?i ofPart ?p . ?i fromSupplier ?s . ?i returnFlag ?f",
    # encyclopedic
    "enc_y1": "?p label ?n . ?p segment ?g . ?p locatedIn ?c . ?p boughtFrom ?a . ?a basedIn ?c",
    "enc_y2": "?p label ?n . ?p segment ?g . ?p locatedIn ?c . ?p boughtFrom ?a . ?a basedIn ?c . ?p boughtFrom ?a2 . ?a2 basedIn ?c",
    "enc_y3": "?s1 supplies ?p . ?s2 supplies ?p . ?s1 label ?l1 . ?s2 label ?l2",
    "enc_y4": "?p1 label ?l1 . ?p2 label ?l2 . ?p1 boughtFrom ?p2 . ?p1 locatedIn ?c . ?p2 basedIn ?c",
    # life-science
    "lif_b1": "supplier/1 supplies ?o . supplier/2 supplies ?o",
    "lif_b2": "customer/1 bought ?p . ?p brand ?m",
    "lif_b3": "?x type class/Part . ?x label ?l . ?g supplies ?x",
    "lif_b4": "?s basedIn nation/1 . ?s supplies ?p . ?i ofPart ?p . ?i inOrder ?o . ?i fromSupplier ?s2 . ?i returnFlag ?f",
    "lif_b5": "?x kind kind/purchase",
}
#: Queries whose answers are many: compared and timed by an aggregate.
HEAVY = ("uni_q09", "uni_l7", "enc_y3", "div_c3", "lif_b3", "lif_b4", "uni_l2")
FAMILIES = {"L": [f"div_l{k}" for k in range(1, 6)], "S": [f"div_s{k}" for k in range(1, 8)], "F": [f"div_f{k}" for k in range(1, 6)], "C": [f"div_c{k}" for k in range(1, 4)]}


def template(name: str) -> BGP:
    return BGP.parse(TEMPLATES[name])


def sql_of(bgp: BGP) -> str:
    """The pattern as plain SQL over the relational tables: one subquery for each predicate, joined on equal terms."""
    froms, where, columns = [], [], {}
    for k, p in enumerate(bgp):
        alias = f"t{k}"
        if isinstance(p.p, Const):
            froms.append(f"({predicate_sql(p.p.value)}) as {alias}")
        else:
            froms.append(f"({triples_sql()}) as {alias}")
        for slot, t in (("s", p.s), ("p", p.p), ("o", p.o)):
            if slot == "p" and isinstance(t, Const):
                continue
            if isinstance(t, Const):
                where.append(f"{alias}.{slot} = '{t.value}'")
            elif t.name in columns:
                where.append(f"{alias}.{slot} = {columns[t.name]}")
            else:
                columns[t.name] = f"{alias}.{slot}"
    names = ", ".join(f"{c} as {v}" for v, c in columns.items())
    return f"select {names} from {', '.join(froms)}" + (f" where {' and '.join(where)}" if where else "")


@dataclass(frozen=True)
class Slots:
    """What a template's constants may be replaced with, by prefix, given the sizes of the data."""

    nations: int = 25
    regions: int = 5
    customers: int = 150
    suppliers: int = 10
    parts: int = 200

    @classmethod
    def of(cls, store) -> Slots:
        """The sizes of a store's tables: as many subjects as their class has."""
        classes = {"nations": "Nation", "regions": "Region", "customers": "Customer", "suppliers": "Supplier", "parts": "Part"}
        patterns = {k: Pattern(Var("s"), Const("type"), Const(f"class/{c}")) for k, c in classes.items()}
        store.refine_all(patterns.values())
        return cls(**{k: max(1, store.knowledge(p).card) for k, p in patterns.items()})

    def other(self, value: str, rng: random.Random) -> str:
        sizes = {"nation": self.nations, "region": self.regions, "customer": self.customers, "supplier": self.suppliers, "part": self.parts}
        head, slash, _ = value.partition("/")
        if slash and head in sizes:
            return f"{head}/{rng.randrange(sizes[head])}"
        if head == "segment":
            return f"segment/{rng.choice(('AUTOMOBILE', 'BUILDING', 'FURNITURE', 'HOUSEHOLD', 'MACHINERY'))}"
        if head == "flag":
            return f"flag/{rng.choice('ANR')}"
        if head == "brand":
            return f"brand/Brand#{rng.randrange(1, 26)}"
        return value


def varied(bgp: BGP, rng: random.Random, slots: Slots) -> BGP:
    """The template with its constants drawn anew; classes stay."""
    swap = {t: Const(slots.other(t.value, rng)) for p in bgp for t in (p.s, p.o) if isinstance(t, Const) and not t.value.startswith("class/")}
    return BGP(tuple(type(p)(swap.get(p.s, p.s), p.p, swap.get(p.o, p.o)) for p in bgp))


#: Classes that stand in for each other when the type of a node is mutated.
TWINS = {"class/Customer": "class/Supplier", "class/Supplier": "class/Customer", "class/Part": "class/Order", "class/Order": "class/Part"}


def structures(bgp: BGP) -> list[BGP]:
    """Other structures of a template: connected parts of two patterns or more, and other types of its nodes; the whole first."""
    out: dict[str, BGP] = {}
    typed = [k for k, p in enumerate(bgp) if p.p == Const("type") and isinstance(p.o, Const) and p.o.value in TWINS]
    for left in range(len(bgp) - 1):
        for gone in combinations(range(len(bgp)), left):
            kept = [k for k in range(len(bgp)) if k not in gone]
            if len(components(BGP(tuple(bgp.patterns[k] for k in kept)))) > 1:
                continue
            here = [k for k in typed if k in kept]
            for n in range(len(here) + 1):
                for swap in combinations(here, n):
                    new = BGP(tuple(Pattern(p.s, p.p, Const(TWINS[p.o.value])) if k in swap else p for k, p in enumerate(bgp.patterns) if k in kept))
                    out.setdefault(query_text(new), new)
    return list(out.values())


# How many patterns the pool has of each of the fourteen templates; two of them vary in structure.
POOL = dict(zip([f"uni_q{k:02d}" for k in range(1, 15)], (1000, 18, 1000, 1000, 1000, 1, 1000, 1000, 30, 1000, 1000, 1000, 1000, 1), strict=True))


def uni_pool(slots: Slots | None = None, seed: int = 7) -> list[tuple[str, BGP]]:
    """The pool: distinct patterns of every template, as many as POOL says, or as the data have constants for."""
    rng, slots, out = random.Random(seed), slots or Slots(), []
    for name, n in POOL.items():
        bgp = template(name)
        if not any(isinstance(t, Const) and not t.value.startswith("class/") for p in bgp for t in (p.s, p.o)):
            out += [(name, b) for b in (structures(bgp) or [bgp])[:n]]
            continue
        seen = {query_text(bgp): bgp}
        for _ in range(8 * n):
            if len(seen) == n:
                break
            new = varied(bgp, rng, slots)
            seen.setdefault(query_text(new), new)
        out += [(name, b) for b in seen.values()]
    return out


def uni_workload(n: int, seed: int = 7, slots: Slots | None = None) -> list[tuple[str, BGP]]:
    """n queries of the pool, drawn so that each template has its share of patterns."""
    rng, by = random.Random(seed), {}
    for name, bgp in uni_pool(slots, seed):
        by.setdefault(name, []).append(bgp)
    return [(x, rng.choice(by[x])) for x in rng.choices(list(POOL), weights=list(POOL.values()), k=n)]


def div_workload(n: int, families: str = "LSFC", seed: int = 7, mixed: bool = True, slots: Slots | None = None) -> list[tuple[str, BGP]]:
    """n queries of the families: mixed, or one family after the other (drift)."""
    rng, slots = random.Random(seed), slots or Slots()
    if mixed:
        pool = [t for f in families for t in FAMILIES[f]]
        return [(x, varied(template(x), rng, slots)) for x in rng.choices(pool, k=n)]
    each = n // len(families)
    return [(x, varied(template(x), rng, slots)) for f in families for x in rng.choices(FAMILIES[f], k=each)]


#: Pairs of families to train on before a mixed test.
TRAINING = ("CF", "CL", "CS", "FL", "FS", "LS")


def shape_of(bgp: BGP) -> str:
    """star, linear, cyclic or tree: by the variables' graph."""
    subjects = {p.s for p in bgp}
    if len(subjects) == 1:
        return "star"
    nodes = {t for p in bgp for t in (p.s, p.o) if isinstance(t, Var)}
    links = {frozenset((p.s, p.o)) for p in bgp if isinstance(p.s, Var) and isinstance(p.o, Var)}
    if len(links) >= len(nodes):
        return "cyclic"
    degree = {v: sum(v in x for x in links) for v in nodes}
    return "linear" if max(degree.values(), default=0) <= 2 and len(bgp) <= 3 else "tree"
