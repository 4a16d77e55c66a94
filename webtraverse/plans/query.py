"""Conjunctive queries of triple patterns, and what is known of them before any lookup."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.terms import LINKS, LITERAL, LITERALS, URI, uri_of


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Lit:
    """A literal constant: text or number."""

    value: str | float


Term = Var | Lit | int


@dataclass(frozen=True)
class TriplePattern:
    """A constant subject or object is a URI id; a constant predicate is a predicate number."""

    s: Term
    p: Term
    o: Term

    def places(self) -> dict[str, list[str]]:
        """Columns in which each variable stands."""
        found: dict[str, list[str]] = {}
        for column, term in (("s", self.s), ("p", self.p), ("o", self.o)):
            if isinstance(term, Var):
                found.setdefault(term.name, []).append(column)
        return found

    def condition(self) -> Column:
        """Whether a triple instantiates this pattern; columns only, so that it reaches the scan."""
        tests = []
        for column, term in (("s", self.s), ("p", self.p), ("o", self.o)):
            if isinstance(term, Var):
                continue
            if isinstance(term, Lit):
                tests.append(F.col("o_kind") == LITERAL)
                tests.append(F.col("o_str") == term.value if isinstance(term.value, str) else F.col("o_dbl") == term.value)
            else:
                tests.append(F.col(column) == term)
                if column == "o":
                    tests.append(F.col("o_kind") == URI)
        for columns in self.places().values():
            # A predicate stands for its URI when it meets a subject or an object.
            ids = [F.col(c).cast("long") * 16 if c == "p" else F.col(c) for c in columns]
            tests += [ids[0] == other for other in ids[1:]]
        return reduce(lambda a, b: a & b, tests, F.lit(True))

    def bindings(self) -> list[Column]:
        return [(F.col(c[0]).cast("long") * 16 if c[0] == "p" else F.col(c[0])).alias(v) for v, c in self.places().items()]


@dataclass(frozen=True)
class ConjunctiveQuery:
    name: str
    patterns: tuple[TriplePattern, ...]
    extra_seeds: tuple[int, ...] = ()
    seeds_given: tuple[int, ...] | None = None
    variables: tuple[str, ...] = field(init=False)

    def __post_init__(self):
        object.__setattr__(self, "variables", tuple(dict.fromkeys(v for t in self.patterns for v in t.places())))

    @property
    def n(self) -> int:
        return len(self.patterns)

    def seeds(self) -> list[int]:
        """All URIs of the patterns, predicates included (their lookup fails), in the order of appearance."""
        if self.seeds_given is not None:
            return list(self.seeds_given)
        found: dict[int, None] = {}
        for t in self.patterns:
            for place, term in (("s", t.s), ("p", t.p), ("o", t.o)):
                if isinstance(term, int):
                    found[term * 16 if place == "p" else term] = None
        found.update(dict.fromkeys(self.extra_seeds))
        return list(found)

    def variables_of(self, mask: int) -> set[str]:
        return {v for i, t in enumerate(self.patterns) if mask >> i & 1 for v in t.places()}

    def remaining(self, mask: int, i: int) -> int:
        """Variables that pattern ``i`` would bind anew."""
        return len(set(self.patterns[i].places()) - self.variables_of(mask))

    def bound(self, mask: int, i: int) -> int:
        """Variables of pattern ``i`` that are bound already."""
        return len(set(self.patterns[i].places()) & self.variables_of(mask))

    def join_order(self, first: int = 0) -> list[int]:
        """A left-deep order that stays connected where the query is."""
        order, rest = [first], [i for i in range(self.n) if i != first]
        while rest:
            mask = sum(1 << i for i in order)
            best = max(rest, key=lambda i: (self.bound(mask, i), -self.remaining(mask, i), -i))
            order.append(best)
            rest.remove(best)
        return order


def query(name: str, *patterns: tuple) -> ConjunctiveQuery:
    """Terms as text: ``?x`` is a variable, ``type:key`` an entity; a predicate by name; anything else a literal."""

    def term(x, place):
        if isinstance(x, str) and x.startswith("?"):
            return Var(x[1:])
        if place == "p":
            return x if isinstance(x, int) else (LINKS | LITERALS)[x]
        if isinstance(x, str) and ":" in x:
            kind, _, key = x.partition(":")
            return uri_of(int(key), kind)
        return x if isinstance(x, int) and not isinstance(x, bool) else Lit(x)

    return ConjunctiveQuery(name, tuple(TriplePattern(*(term(x, place) for x, place in zip(p, "spo"))) for p in patterns))


WORKLOAD = {
    q.name: q
    for q in (
        query("q1", ("?o", "o_cust", "customer:7"), ("?l", "l_order", "?o"), ("?l", "l_part", "?p")),
        query("q2", ("?c", "c_nation", "nation:3"), ("?o", "o_cust", "?c")),
        query("q3", ("orders:11", "o_cust", "?c"), ("?c", "c_nation", "?n"), ("?n", "in_region", "?r"), ("?s", "s_nation", "?n")),
        query("q4", ("?p", "p_brand", "brand:1"), ("?l", "l_part", "?p"), ("?l", "l_supp", "?s"), ("?s", "s_nation", "?n")),
        query("q5", ("?n", "in_region", "region:2"), ("?s", "s_nation", "?n"), ("?l", "l_supp", "?s"), ("?l", "l_order", "?o"), ("?o", "o_cust", "?c")),
        query("q6", ("?l", "l_order", "orders:5"), ("?l", "l_part", "?p"), ("?l", "l_supp", "?s"), ("?p", "p_brand", "?b"), ("?s", "s_nation", "?n")),
        query("q7", ("?c", "c_nation", "nation:3"), ("?c", "c_mktsegment", "BUILDING"), ("?o", "o_cust", "?c"), ("?o", "o_orderstatus", "F")),
    )
}
SIX = ("q1", "q2", "q3", "q4", "q5", "q6")


# SQL twins ----------------------------------------------------------------------------------------------------------


def _cell(term: Term, place: str) -> str | None:
    if isinstance(term, int):
        return f"{place} = {term}"
    return None


def pattern_sql(t: TriplePattern, source: str = "web") -> str:
    """Matches of a pattern among link triples, as SQL."""
    tests = [x for x in (_cell(t.s, "s"), _cell(t.p, "p"), _cell(t.o, "o")) if x]
    cols = [f"{'p::bigint * 16' if c[0] == 'p' else c[0]} as {v}" for v, c in t.places().items()]
    for c in t.places().values():
        ids = ["p::bigint * 16" if x == "p" else x for x in c]
        tests += [f"{ids[0]} = {other}" for other in ids[1:]]
    return f"select {', '.join(['doc', *cols])} from {source}" + (" where " + " and ".join(tests) if tests else "")


def join_sql(q: ConjunctiveQuery, extra: str = "", source: str = "web") -> str:
    """All bag solutions with the document of each ingredient (d0, d1, ...), as SQL."""
    order, seen, text = q.join_order(), {}, ""
    for n, i in enumerate(order):
        shared = [v for v in q.patterns[i].places() if v in seen]
        on = " and ".join(f"{seen[v]}.{v} = m{i}.{v}" for v in shared) or "true"
        text += f" from ({pattern_sql(q.patterns[i], source)}) m{i}" if n == 0 else f" join ({pattern_sql(q.patterns[i], source)}) m{i} on {on}"
        for v in q.patterns[i].places():
            seen.setdefault(v, f"m{i}")
    cols = [f"{seen[v]}.{v} as {v}" for v in q.variables] + [f"m{i}.doc as d{i}" for i in range(q.n)]
    return f"select {', '.join(cols)}{extra}{text}"
