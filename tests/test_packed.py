"""A subweb held as arrays: the same execution as over lists, in a fraction of the memory."""

import random
import tracemalloc

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from test_hubs import hub

from webtraverse.operators.routing import Routing
from webtraverse.plans import experiments
from webtraverse.plans.approaches import APPROACHES, LITERAL_HYBRIDS
from webtraverse.plans.packed import PackedWeb
from webtraverse.plans.query import WORKLOAD, ConjunctiveQuery, TriplePattern, Var
from webtraverse.plans.simulate import SubWeb, cell, documents_of

ALL = APPROACHES | LITERAL_HYBRIDS
X, Y, Z, P = Var("x"), Var("y"), Var("z"), Var("p")
QUERIES = (
    ConjunctiveQuery("path", (TriplePattern(X, 10, Y), TriplePattern(Y, 11, Z)), seeds_given=(16, 32, 160)),
    ConjunctiveQuery("star", (TriplePattern(X, 10, Y), TriplePattern(X, P, Z), TriplePattern(Z, 11, Y)), seeds_given=(48,)),
    ConjunctiveQuery("loop", (TriplePattern(X, 10, X), TriplePattern(X, 11, Y)), seeds_given=(16, 32, 48)),
)


def rows(documents):
    found = [(d, *t) for d, triples in documents.items() for t in triples] + [(d, None, None, None) for d, triples in documents.items() if not triples]
    random.Random(1).shuffle(found)
    return [tuple(c) for c in zip(*found)]


def batches(documents, size=7):
    table = pa.table(dict(zip(("doc", "s", "p", "o"), (pa.array(c, pa.int64()) for c in rows(documents)))))
    return iter(table.to_batches(size))


def random_web(seed, n=24):
    r = random.Random(seed)
    uris = [k * 16 + 3 for k in range(n)] + [16, 32, 48]
    docs = {u: [] for u in uris if r.random() < 0.9}
    for _ in range(6 * n):
        s, o = r.choice(uris), r.choice(uris) if r.random() < 0.9 else -r.randrange(1, 6)
        t = (s, r.choice((10, 10, 11, 12)), o)
        for d in {s, o} if r.random() < 0.5 else {r.choice((s, o))}:
            if d in docs:
                docs[d].append(t)
    return {d: sorted(t) for d, t in docs.items()}


def outcome(run):
    return run.trace, run.solutions, list(run.times), run.routed, run.priority_changes, run.attempted, run.rounds, run.by_operator


@pytest.mark.parametrize("name", ALL)
def test_arrays_execute_as_lists(name):
    for seed in range(12):
        documents = random_web(seed)
        lists, arrays = SubWeb(documents), PackedWeb.of_batches(batches(documents))
        for q in QUERIES:
            for options in ({}, {"batch": 3}, {"bag": False, "routing": Routing("lr_mc_ms")}, {"graph": "matching", "seed": 5}):
                assert outcome(cell(lists, q, ALL[name], **options)) == outcome(cell(arrays, q, ALL[name], **options))
    few = hub(400)
    assert outcome(cell(few, WORKLOAD["q2"], ALL[name])) == outcome(cell(PackedWeb.of_batches(batches(few.documents, 1_000)), WORKLOAD["q2"], ALL[name]))


def test_times_are_kept_without_solutions():
    documents = random_web(3)
    web = PackedWeb.of_batches(batches(documents))
    kept, bare = cell(web, QUERIES[0], ALL["rel2"]), cell(web, QUERIES[0], ALL["rel2"], keep=False)
    assert not bare.solutions and bare.times == kept.times and list(kept.times) == [t for _, t, _ in kept.solutions] and bare.trace == kept.trace


def test_a_subweb_without_triples_or_documents():
    nothing = PackedWeb.of_batches(iter(()))
    assert cell(nothing, WORKLOAD["q2"], ALL["fifo"]).trace == []
    nation = WORKLOAD["q2"].seeds()[1]
    assert cell(PackedWeb.of_batches(batches({nation: []})), WORKLOAD["q2"], ALL["rcc2"]).trace == [nation]


@pytest.mark.parametrize("name", ["indegree", "partial_rel2"])
def test_a_cell_takes_less_than_half_the_memory_of_lists(name):
    """At 60 times sf0.1 two cells share what an executor leaves to Python, about 1 GB."""
    web = hub(3_000)
    for c in list(web.documents):
        if c % 16 == 6:  # lines of an order, which no query follows
            web.documents[c] = sorted([*web.documents[c], *((c * 64 + k * 16 + 7, 5, c) for k in range(4))])
    columns = dict(zip(("doc", "s", "p", "o"), rows(web.documents)))
    given = {k: np.array([-1 if x is None else x for x in v]) for k, v in columns.items()}

    def peak(make, **options):
        tracemalloc.start()
        cell(make(), WORKLOAD["q2"], ALL[name], **options)
        most = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        return most

    lists = peak(lambda: SubWeb(documents_of(pd.DataFrame(given))))
    assert 2 * peak(lambda: PackedWeb.of_batches(batches_of(given)), keep=False) < lists


def batches_of(given, size=10_000):
    n = len(given["doc"])
    return (pa.record_batch({k: v[i : i + size] for k, v in given.items()}) for i in range(0, n, size))


def test_cells_of_the_grid_hold_arrays(spark, small, monkeypatch):
    monkeypatch.setattr(experiments, "SubWeb", None)  # lists of tuples would not fit
    got = experiments.grid(spark, small, ("q2",), (experiments.testweb.CORPUS_LIKE,), ("fifo", "partial_rcc2", "oracle_rcc"))
    assert {r["approach"] for r in got.where("n_docs > 0").collect()} == {"fifo", "partial_rcc2", "oracle_rcc"}
