"""Which pattern operator a partial solution is sent to next.

A policy narrows the operators that are still uncovered, rule by rule; what remains is chosen from at random (seeded), or by
the lowest pattern number where no seed is given. The rules that look at variables alone depend on the covered patterns only, so
their outcome is a small table known before the run.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import permutations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..plans.query import ConjunctiveQuery

#: rules: lr least remaining variables, mc most bound variables, li/mi least/most items in the index, ls/ms least/most selective.
POLICIES = {
    "uniform": (),
    "lr": ("lr",),
    "lr_li": ("lr", "li"),
    "lr_mi": ("lr", "mi"),
    "lr_mc": ("lr", "mc"),
    "lr_mc_li": ("lr", "mc", "li"),
    "lr_mc_mi": ("lr", "mc", "mi"),
    "lr_mc_ls": ("lr", "mc", "ls"),
    "lr_mc_ms": ("lr", "mc", "ms"),
}
DEFAULT = "lr_mi"


@dataclass(frozen=True)
class Routing:
    policy: str = DEFAULT
    order: tuple[int, ...] | None = None
    seed: int | None = None

    @classmethod
    def static(cls, order) -> "Routing":
        """A left-deep plan: operators are visited in one fixed order."""
        return cls("static", tuple(order))

    @property
    def rules(self) -> tuple[str, ...]:
        return () if self.order is not None else POLICIES[self.policy]

    def fixed_choice(self, query: ConjunctiveQuery, mask: int) -> list[int]:
        """Operators left by the rules that need no run-time state."""
        open_ = [i for i in range(query.n) if not mask >> i & 1]
        if self.order is not None:
            return [next(i for i in self.order if i in open_)]
        for rule in self.rules:
            if rule == "lr":
                least = min(query.remaining(mask, i) for i in open_)
                open_ = [i for i in open_ if query.remaining(mask, i) == least]
            elif rule == "mc":
                most = max(query.bound(mask, i) for i in open_)
                open_ = [i for i in open_ if query.bound(mask, i) == most]
        return open_

    def pick(self, among: list[int], sizes, selectivity, draw) -> int:
        """The choice at run time: ``sizes`` and ``selectivity`` by operator, ``draw`` gives a number below its argument."""
        for rule in self.rules:
            if len(among) == 1:
                break
            if rule in ("li", "mi"):
                best = (min if rule == "li" else max)(sizes[i] for i in among)
                among = [i for i in among if sizes[i] == best]
            elif rule in ("ls", "ms"):
                best = (min if rule == "ls" else max)(selectivity[i] for i in among)
                among = [i for i in among if selectivity[i] == best]
        return among[0] if len(among) == 1 or self.seed is None else among[draw(len(among))]

    def column(self, query: ConjunctiveQuery, mask: int, history: dict[int, float] | None = None) -> Column:
        """The same choice as a column, for partials that cover ``mask``; they carry ``sizes`` and ``ts``.

        Selectivities are those of earlier batches, given as ``history``.
        """
        among = self.fixed_choice(query, mask)
        if {"ls", "ms"} & set(self.rules):
            kept = {i: (history or {}).get(i, 1.0) for i in among}
            best = (min if "ls" in self.rules else max)(kept.values())
            among = [i for i in among if kept[i] == best]
        if len(among) == 1:
            return F.lit(among[0])
        tie = (lambda i: F.lit(i)) if self.seed is None else (lambda i: F.xxhash64(F.lit(self.seed), "ts", F.lit(mask), F.lit(i)))
        if {"li", "mi"} & set(self.rules):
            sign = -1 if "mi" in self.rules else 1
            return F.array_min(F.array(*[F.struct((F.col("sizes")[i] * sign).alias("size"), tie(i).alias("tie"), F.lit(i).alias("op")) for i in among]))["op"]
        return F.array_min(F.array(*[F.struct(tie(i).alias("tie"), F.lit(i).alias("op")) for i in among]))["op"]


def all_static(query: ConjunctiveQuery) -> list[Routing]:
    return [Routing.static(p) for p in permutations(range(query.n))]


def selectivity(incoming: int, returned: int) -> float:
    """Incoming over returned: high where an operator prunes much; 1 while nothing is known."""
    return (incoming / returned if returned else float("inf")) if incoming else 1.0
