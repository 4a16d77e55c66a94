"""The worked example, invariants, and a replay of every choice by a queue written apart from the simulator."""

import random
from itertools import product

import numpy as np
import pytest

from webtraverse.operators.routing import POLICIES, Routing, all_static
from webtraverse.plans.approaches import APPROACHES, LITERAL_HYBRIDS, Arrival, LinkGraph
from webtraverse.plans.query import ConjunctiveQuery, Lit, TriplePattern, Var
from webtraverse.plans.simulate import Stop, SubWeb, cell, response_times

X, Y, Z = Var("x"), Var("y"), Var("z")
CHAIN = ConjunctiveQuery("chain", (TriplePattern(1, 10, X), TriplePattern(X, 11, Y), TriplePattern(Y, 12, Z)), seeds_given=(1,))
DOCS = {
    1: [(1, 10, 2), (1, 10, 3)], 2: [(2, 11, 4), (2, 11, 5)], 3: [(3, 11, 6), (3, 11, 10)], 4: [], 5: [(5, 12, 7)], 6: [(6, 12, 8)], 7: [], 8: [(9, 12, 8), (6, 12, 8)], 9: [],
}
WEB = SubWeb(DOCS, predicates=False)
ALL = APPROACHES | LITERAL_HYBRIDS | {"pagerank": LinkGraph("pagerank", refresh=1)}

EXPECTED = {
    ("fifo", "breadth_first", "indegree"): ([1, 2, 3, 4, 5, 6, 7, 8, 9], [5, 6, 8], 17),
    ("depth_first",): ([1, 2, 4, 5, 7, 3, 6, 8, 9], [4, 7, 8], 18),
    ("oracle_rcc",): ([1, 3, 2, 6, 5, 8, 4, 7, 9], [4, 5, 6], 17),
    ("partial", "partial_decay"): ([1, 2, 4, 5, 3, 7, 6, 8, 9], [4, 7, 8], 18),
    ("rcc1", "rcc2", "rel1", "rel2", *LITERAL_HYBRIDS): ([1, 2, 3, 4, 5, 7, 6, 8, 9], [5, 7, 8], 17),
    ("partial_rcc1", "partial_rel1"): ([1, 2, 4, 5, 3, 7, 6, 8, 9], [4, 7, 8], 18),
    ("partial_rcc2", "partial_rel2"): ([1, 2, 4, 5, 7, 3, 6, 8, 9], [4, 7, 8], 18),
}


@pytest.mark.parametrize("name,order,times,routed", [(n, *e) for names, e in EXPECTED.items() for n in names])
def test_worked_example(name, order, times, routed):
    run = cell(WEB, CHAIN, ALL[name])
    assert (run.trace, sorted(t for _, t, _ in run.solutions), run.routed) == (order, times, routed)
    assert sorted((s, tuple(sorted(set(d)))) for s, _, d in run.solutions) == [((2, 5, 7), (1, 2, 5)), ((3, 6, 8), (1, 3, 6)), ((3, 6, 8), (1, 3, 8))]
    assert run.rcc() == {1: 3, 3: 2, 2: 1, 5: 1, 6: 1, 8: 1}
    assert response_times(run) == {"relRT1st": times[0] / 9, "relRT50": times[1] / 9, "relRTCmpl": times[2] / 9}


def test_registered_pagerank_ranks_after_every_lookup():
    web = web_of(random.Random(3), links=220)
    every, sparse, own = (cell(web, CHAIN, a).trace for a in (LinkGraph("pagerank", refresh=1), LinkGraph("pagerank", refresh=25), APPROACHES["pagerank"]))
    assert own == every != sparse


def web_of(rng, n=40, links=110):
    docs = {i: [] for i in range(1, n + 1)}
    for _ in range(links):
        s, p, o = rng.randint(1, n + 4), rng.choice([10, 11, 12]), rng.randint(1, n + 4)
        for d in {x for x in (s, o) if rng.random() < 0.7 and x in docs}:
            docs[d].append((s, p, o))
    return SubWeb({d: sorted(set(t)) for d, t in docs.items()}, predicates=False)


def brute_force(web, query, bag=True):
    """All solutions over the reachable documents by nested loops."""
    reach = set(cell(web, query, Arrival("fifo")).trace)
    triples = [(d, t) for d in sorted(reach) for t in web.documents[d]]
    if not bag:
        triples = [(0, t) for t in sorted({t for _, t in triples})]
    found = [{}]
    for pattern in query.patterns:
        more = []
        for binding in found:
            for _, t in triples:
                b, ok = dict(binding), True
                for term, value in zip((pattern.s, pattern.p, pattern.o), t):
                    if isinstance(term, Var):
                        ok &= b.setdefault(term.name, value) == value
                    else:
                        ok &= (term.value if isinstance(term, Lit) else term) == value
                if ok:
                    more.append(b)
        found = more
    return sorted(tuple(b[v] for v in query.variables) for b in found)


@pytest.mark.parametrize("number", range(6))
def test_every_approach_and_routing_agrees(number):
    rng = random.Random(number)
    web = web_of(rng)
    expected, base = brute_force(web, CHAIN), cell(web, CHAIN, APPROACHES["fifo"])
    first = min((t for _, t, _ in base.solutions), default=None)
    for name, approach in ALL.items():
        run = cell(web, CHAIN, approach, seed=3)
        assert sorted(s for s, _, _ in run.solutions) == expected and set(run.trace) == set(base.trace) and len(run.trace) == len(set(run.trace))
        place = {d: i + 1 for i, d in enumerate(run.trace)}
        assert all(t == max(place[d] for d in docs) for _, t, docs in run.solutions)
        if approach.family == "solution":
            assert min((t for _, t, _ in run.solutions), default=None) == first
            assert first is None or run.trace[:first] == base.trace[:first]
        if rt := response_times(run):
            assert 0 < rt["relRT1st"] <= rt["relRT50"] <= rt["relRTCmpl"] <= 1
    assert cell(web, CHAIN, APPROACHES["breadth_first"]).trace == base.trace
    for routing in [Routing(p, seed=s) for p in POLICIES for s in (None, 1)] + all_static(CHAIN):
        run = cell(web, CHAIN, APPROACHES["fifo"], routing)
        assert sorted(s for s, _, _ in run.solutions) == expected
        assert sorted(t for _, t, _ in run.solutions) == sorted(t for _, t, _ in base.solutions)
    assert sorted(set(brute_force(web, CHAIN))) == brute_force(web, CHAIN, bag=False) == sorted(s for s, _, _ in cell(web, CHAIN, APPROACHES["fifo"], bag=False).solutions)


def naive_scores(web, trace, solutions, seen, measure, steps):
    """Scores of queued URIs from scratch."""
    out = {d: {u for t in web.documents[d] for u in web.uris(t)} - {d} for d in trace}
    rcc = {}
    for _, t, docs in solutions:
        if t <= len(trace):
            for d in set(docs):
                rcc[d] = rcc.get(d, 0) + 1
    scores = {}
    for v in seen:
        one = {w for w in trace if v in out[w]}
        near = one | ({w for w in trace for m in one if m in out[w]} if steps == 2 else set())
        near.discard(v)
        scores[v] = sum(rcc.get(w, 0) if measure == "rcc" else rcc.get(w, 0) > 0 for w in near)
    return scores


@pytest.mark.parametrize("name", ["rcc1", "rcc2", "rel1", "rel2", "indegree"])
def test_replay_of_every_choice(name):
    """At each step the chosen URI has the highest score, and among equals it arrived first."""
    for number in range(12):
        web = web_of(random.Random(100 + number), 25, 80)
        run = cell(web, CHAIN, APPROACHES[name])
        arrived, seen_docs = [1], []
        for step, doc in enumerate(run.trace):
            queued = [u for u in arrived if u not in seen_docs and u in web.documents]
            if name == "indegree":
                scores = {u: sum(any(u in web.uris(t) for t in web.documents[w]) for w in seen_docs if w != u) for u in queued}
            else:
                scores = naive_scores(web, seen_docs, [x for x in run.solutions if x[1] <= step], queued, name[:3], int(name[3]))
            assert doc == max(queued, key=lambda u: (scores[u], -arrived.index(u)))
            seen_docs.append(doc)
            for t in web.documents[doc]:
                if any(p.p == t[1] and (isinstance(p.s, Var) or p.s == t[0]) for p in CHAIN.patterns):
                    arrived += [u for u in web.uris(t) if u not in arrived]


def partial_coverage(found, order, n):
    """Per URI the most patterns covered by a partial that was sent on under a static plan: the newest match meets older ones in plan order."""
    best = {}
    for size in range(1, n):
        for start in range(n):
            chosen = [start, *[i for i in order if i != start][: size - 1]]
            for rows in product(*[[m for m in found if m[1] == i] for i in chosen]):
                if max(rows)[:2] != rows[0][:2] or any(r[0] > rows[0][0] for r in rows):
                    continue
                binding, ok = {}, True
                for _, _, values in rows:
                    for name, value in values:
                        ok &= binding.setdefault(name, value) == value
                if ok:
                    for value in binding.values():
                        best[value] = max(best.get(value, 0), size)
    return best


@pytest.mark.parametrize("name", ["partial", "partial_decay", *(a for a in ALL if a.startswith("partial_") and a != "partial_decay")])
@pytest.mark.parametrize("plan", all_static(CHAIN), ids=lambda r: "".join(map(str, r.order)))
def test_replay_of_partials_and_hybrids(name, plan):
    """The choice at each step from all partials, contributions and links there are by then, counted anew."""
    moved = 0
    for number in range(3):
        web = web_of(random.Random(200 + number), 25, 80)
        run = cell(web, CHAIN, ALL[name], plan)
        arrived, taken, found, start = [1], [], [], {1: 0.0}
        for step, doc in enumerate(run.trace):
            queued = [u for u in arrived if u not in taken and u in web.documents]
            covered = partial_coverage(found, plan.order, CHAIN.n)
            if name in ("partial", "partial_decay"):
                scores = {u: max(start[u] if name == "partial_decay" else 0, covered.get(u, start[u] if name == "partial_decay" else 0)) for u in queued}
            else:
                near = naive_scores(web, taken, [x for x in run.solutions if x[1] <= step], queued, name.split("_")[1][:3], int(name.split("_")[1][3]))
                scores = {u: covered.get(u, 0) * (near[u] + (not name.endswith("product"))) for u in queued}
            assert doc == max(queued, key=lambda u: (scores[u], -arrived.index(u)))
            moved += doc != queued[0]
            taken.append(doc)
            for place, t in enumerate(web.documents[doc]):
                hits = [i for i, p in enumerate(CHAIN.patterns) if p.p == t[1] and (isinstance(p.s, Var) or p.s == t[0])]
                for i in hits:
                    names = [(x.name, v) for x, v in ((CHAIN.patterns[i].s, t[0]), (CHAIN.patterns[i].o, t[2])) if isinstance(x, Var)]
                    found.append(((step, place), i, names))
                for u in web.uris(t) if hits else ():
                    if u not in arrived:
                        arrived.append(u)
                        start[u] = scores[doc] - 1
    assert moved


def test_replay_of_pagerank():
    """Each choice has the greatest stationary probability, solved for directly, on the graph known by then."""
    for number in range(4):
        web = web_of(random.Random(300 + number), 25, 80)
        run = cell(web, CHAIN, APPROACHES["pagerank"])
        arrived, taken = [1], []
        for doc in run.trace:
            queued = [u for u in arrived if u not in taken and u in web.documents]
            out = {d: {u for t in web.documents[d] for u in web.uris(t)} - {d} for d in taken}
            known = sorted(set(taken) | {u for u in arrived if u not in taken} | {v for own in out.values() for v in own})
            place, n = {v: i for i, v in enumerate(known)}, len(known)
            step = np.full((n, n), 1.0 / n)
            for d, own in out.items():
                if own:
                    step[:, place[d]] = 0
                    step[[place[v] for v in own], place[d]] = 1 / len(own)
            rank = np.linalg.solve(np.eye(n) - 0.85 * step, np.full(n, 0.15 / n))
            assert rank[place[doc]] >= max(rank[place[u]] for u in queued) - 1e-6
            taken.append(doc)
            for t in web.documents[doc]:
                if any(p.p == t[1] and (isinstance(p.s, Var) or p.s == t[0]) for p in CHAIN.patterns):
                    arrived += [u for u in web.uris(t) if u not in arrived]


def test_micro_cases():
    a, b = TriplePattern(1, 10, X), TriplePattern(X, 10, Y)
    twice = ConjunctiveQuery("twice", (a, TriplePattern(1, 10, X)), seeds_given=(1,))
    same = SubWeb({1: [(1, 10, 2)], 2: [(1, 10, 2)]}, predicates=False)
    one = ConjunctiveQuery("one", (a,), seeds_given=(1,))
    assert len(cell(same, one, APPROACHES["fifo"]).solutions) == 2 and len(cell(same, one, APPROACHES["fifo"], bag=False).solutions) == 1
    assert len(cell(same, twice, APPROACHES["fifo"]).solutions) == 4 and len(cell(same, twice, APPROACHES["fifo"], bag=False).solutions) == 1
    loop = SubWeb({1: [(1, 10, 1), (1, 10, 2)], 2: [(2, 10, 1)]}, predicates=False)
    assert sorted(cell(loop, ConjunctiveQuery("self", (TriplePattern(X, 10, X),), seeds_given=(1,)), APPROACHES["fifo"]).solutions) == [((1,), 1, (1,))]
    assert cell(loop, ConjunctiveQuery("path", (a, b), seeds_given=(1,)), APPROACHES["fifo"]).trace == [1, 2]
    apart = ConjunctiveQuery("apart", (TriplePattern(1, 10, X), TriplePattern(2, 10, Y)), seeds_given=(1, 2))
    assert len(cell(loop, apart, APPROACHES["fifo"]).solutions) == 2
    lit = SubWeb({1: [(1, 10, "red"), (1, 11, 5)], 5: []}, predicates=False)
    assert cell(lit, ConjunctiveQuery("lit", (TriplePattern(1, 10, Lit("red")), TriplePattern(1, 11, Y)), seeds_given=(1,)), APPROACHES["partial"]).solutions == [((5,), 1, (1, 1))]
    alias = SubWeb({1: [(1, 10, 7), (1, 10, 8)], 9: [(7, 10, 1)]}, predicates=False, resolve={7: 9, 8: 9})
    assert cell(alias, ConjunctiveQuery("alias", (a, b), seeds_given=(1,)), APPROACHES["fifo"]).trace == [1, 9]
    variable = ConjunctiveQuery("pred", (TriplePattern(1, Y, X),), seeds_given=(1,))
    run = cell(SubWeb({1: [(1, 10, 2)], 2: []}), variable, APPROACHES["fifo"])
    assert run.solutions == [((160, 2), 1, (1,))] or run.solutions == [((2, 160), 1, (1,))]
    assert run.attempted == 3 and run.trace == [1, 2]
    assert response_times(cell(SubWeb({1: []}), CHAIN, APPROACHES["fifo"])) is None
    assert len(cell(WEB, CHAIN, APPROACHES["fifo"], stop=Stop(k=1)).solutions) == 1
    assert cell(WEB, CHAIN, APPROACHES["rel1"], feedback=False).trace == cell(WEB, CHAIN, APPROACHES["fifo"]).trace
