"""The seventeen ways to order lookups, by what they look at.

Non-adaptive: arrival, random, depth, breadth, an oracle. Adaptive ones follow the link graph, the partial solutions that are routed,
the documents that contributed to solutions, or both of the latter.
"""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Approach:
    """How the priority of a queued URI is made; a greater number is looked up earlier, ties go by arrival."""

    name: str
    family: str

    @property
    def adaptive(self) -> bool:
        return self.family not in ("arrival", "oracle")

    @property
    def uses_partials(self) -> bool:
        return self.family in ("partial", "hybrid")

    @property
    def uses_solutions(self) -> bool:
        return self.family in ("solution", "hybrid")


@dataclass(frozen=True)
class Arrival(Approach):
    """fifo, random, depth_first and breadth_first; ``step`` is added to the parent's priority."""

    family: str = "arrival"
    step: int = 0
    draw: bool = False


@dataclass(frozen=True)
class Oracle(Approach):
    """Final contribution counts, known from a dry run."""

    name: str = "oracle_rcc"
    family: str = "oracle"


@dataclass(frozen=True)
class LinkGraph(Approach):
    """indegree or pagerank on what is known of the link graph; ``refresh`` lookups pass between two rankings."""

    family: str = "graph"
    damping: float = 0.85
    tolerance: float = 1e-8
    rounds: int = 60
    warm: bool = True
    refresh: int = 1


@dataclass(frozen=True)
class Partial(Approach):
    """The most patterns covered by a routed partial that mentions the URI; ``inherit``: start at the parent's last priority less one."""

    family: str = "partial"
    inherit: bool = False
    count_complete: bool = False


@dataclass(frozen=True)
class SolutionAware(Approach):
    """Contribution counts (rcc), or the number of contributors (rel), among in-neighbours of up to ``steps`` steps."""

    family: str = "solution"
    measure: str = "rcc"
    steps: int = 1


@dataclass(frozen=True)
class Hybrid(Approach):
    """The partial score times the solution-aware one. ``product`` is literal: nothing counts before the first solution. ``smoothed``
    multiplies by one more than the score, so the partial score leads until then."""

    family: str = "hybrid"
    measure: str = "rcc"
    steps: int = 1
    combine: str = "smoothed"
    count_complete: bool = False


APPROACHES: dict[str, Approach] = {
    a.name: a
    for a in (
        Arrival("fifo"),
        Arrival("random", draw=True),
        Arrival("depth_first", step=1),
        Arrival("breadth_first", step=-1),
        Oracle(),
        LinkGraph("pagerank"),
        LinkGraph("indegree"),
        Partial("partial"),
        Partial("partial_decay", inherit=True),
        *(SolutionAware(f"{m}{k}", measure=m, steps=k) for m in ("rcc", "rel") for k in (1, 2)),
        *(Hybrid(f"partial_{m}{k}", measure=m, steps=k) for m in ("rcc", "rel") for k in (1, 2)),
    )
}
LITERAL_HYBRIDS = {f"partial_{m}{k}_product": Hybrid(f"partial_{m}{k}_product", measure=m, steps=k, combine="product") for m in ("rcc", "rel") for k in (1, 2)}
BASELINE = "fifo"
COMPARED = tuple(a for a in APPROACHES if a not in ("fifo", "breadth_first", "pagerank"))
