"""Query model: terms, triple patterns, basic graph patterns and what may surround them."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace


@dataclass(frozen=True, order=True)
class Var:
    name: str

    def __str__(self) -> str:
        return f"?{self.name}"


@dataclass(frozen=True, order=True)
class Const:
    value: str

    def __str__(self) -> str:
        return self.value


Term = Var | Const


def term(x: Term | str) -> Term:
    """`?x` is a variable, anything else a constant."""
    return x if isinstance(x, Var | Const) else Var(x[1:]) if x.startswith("?") else Const(x)


@dataclass(frozen=True)
class Pattern:
    s: Term
    p: Term
    o: Term

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t.name for t in (self.s, self.p, self.o) if isinstance(t, Var)))

    def slots(self, name: str) -> str:
        """Which of s, p, o hold the variable."""
        return "".join(k for k, t in zip("spo", (self.s, self.p, self.o), strict=True) if t == Var(name))

    def __str__(self) -> str:
        return f"{self.s} {self.p} {self.o}"


def pattern(s: Term | str, p: Term | str, o: Term | str) -> Pattern:
    return Pattern(term(s), term(p), term(o))


@dataclass(frozen=True)
class BGP:
    patterns: tuple[Pattern, ...]

    @staticmethod
    def of(*triples: tuple[str, str, str]) -> BGP:
        return BGP(tuple(pattern(*t) for t in triples))

    @staticmethod
    def parse(text: str) -> BGP:
        """`?x bought part/1 . ?x segment ?g`: patterns with blank-separated terms."""
        return BGP(tuple(pattern(*t.split()) for t in text.split(" . ")))

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for p in self.patterns for v in p.variables))

    def __iter__(self) -> Iterator[Pattern]:
        return iter(self.patterns)

    def __len__(self) -> int:
        return len(self.patterns)


def is_subject_star(bgp: BGP) -> bool:
    """All patterns share their subject: every answer lies at that subject's home."""
    return len({p.s for p in bgp}) == 1


def query_graph(bgp: BGP) -> dict[Term, list[int]]:
    """Vertex (variable or constant at a subject or object) to the patterns it touches."""
    out: dict[Term, list[int]] = {}
    for k, p in enumerate(bgp):
        for v in dict.fromkeys((p.s, p.o)):
            out.setdefault(v, []).append(k)
    return out


def components(bgp: BGP) -> list[BGP]:
    """Parts of the pattern that share no variable with each other; constants don't connect."""
    left, out = list(bgp.patterns), []
    while left:
        part, seen = [left.pop(0)], set()
        seen |= set(part[0].variables)
        grown = True
        while grown:
            grown = [p for p in left if seen & set(p.variables)]
            part += grown
            left = [p for p in left if p not in grown]
            for p in grown:
                seen |= set(p.variables)
        out.append(BGP(tuple(part)))
    return out


@dataclass(frozen=True)
class Query:
    bgp: BGP
    select: tuple[str, ...] = ()
    distinct: bool = False
    filters: tuple[str, ...] = ()
    optional: tuple[BGP, ...] = ()
    order_by: tuple[tuple[str, bool], ...] = ()  # (variable, descending)
    limit: int | None = None
    offset: int = 0
    ask: bool = False

    @property
    def projection(self) -> tuple[str, ...]:
        names = self.bgp.variables + tuple(v for b in self.optional for v in b.variables)
        return self.select or tuple(dict.fromkeys(names))


@dataclass(frozen=True)
class Match:
    """A query put together call by call; every call gives a new one."""

    query: Query = field(default_factory=lambda: Query(BGP(())))

    def match(self, *triples: tuple[str, str, str]) -> Match:
        return Match(replace(self.query, bgp=BGP(self.query.bgp.patterns + BGP.of(*triples).patterns)))

    def optional(self, *triples: tuple[str, str, str]) -> Match:
        return Match(replace(self.query, optional=(*self.query.optional, BGP.of(*triples))))

    def filter(self, condition: str) -> Match:
        return Match(replace(self.query, filters=(*self.query.filters, condition)))

    def select(self, *names: str) -> Match:
        return Match(replace(self.query, select=tuple(n.lstrip("?") for n in names)))

    def distinct(self) -> Match:
        return Match(replace(self.query, distinct=True))

    def order_by(self, *names: str) -> Match:
        return Match(replace(self.query, order_by=tuple((n.lstrip("-?"), n.startswith("-")) for n in names)))

    def limit(self, n: int, offset: int = 0) -> Match:
        return Match(replace(self.query, limit=n, offset=offset))


def distinct_terms(patterns: Iterable[Pattern]) -> list[Term]:
    return list(dict.fromkeys(t for p in patterns for t in (p.s, p.o)))


def query_text(bgp: BGP) -> str:
    return "SELECT * WHERE { " + " . ".join(map(str, bgp)) + " }"
