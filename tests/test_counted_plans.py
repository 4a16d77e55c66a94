"""Plans counted in tables equal their simulation."""

from random import Random

import pytest

from webtraverse.plans import counted, experiments
from webtraverse.plans.approaches import APPROACHES
from webtraverse.plans.query import WORKLOAD, query
from webtraverse.plans.simulate import SubWeb, cell
from webtraverse.sources import testweb


def test_a_cell_too_large_for_a_task_is_counted(spark, small, monkeypatch):
    names = experiments.routing_names("q1")
    given = experiments.cell_inputs(spark, small, ("q1",), (testweb.CORPUS_LIKE,))
    ask = lambda: sorted(map(tuple, experiments.grid(spark, small, ("q1",), (testweb.CORPUS_LIKE,), ("fifo",), names, 2, given).collect()))
    simulated = ask()
    monkeypatch.setattr(experiments, "MOST_DOCUMENTS", 3)
    monkeypatch.setattr(experiments, "MOST_LOOKUPS", 3)
    monkeypatch.setattr(experiments, "cell", None)
    assert ask() == simulated and len(simulated) == len(names) + 1


SHAPES = (
    query("star", ("?a", "o_cust", "customer:1"), ("?a", "l_order", "?b"), ("?b", "l_part", "?c")),
    query("loop", ("?a", 4, "?b"), ("?b", 4, "?c"), ("?c", "?p", "?a")),
    query("two", ("?a", "o_cust", "customer:1"), ("?a", "l_order", "?b")),
    query("one", ("?a", "o_cust", "customer:1")),
)


@pytest.mark.parametrize("q", SHAPES, ids=lambda q: q.name)
def test_any_web_is_counted_as_it_is_simulated(spark, q):
    """Triples that match several patterns, stand in several documents or name what is no document; documents without triples."""
    rng, start = Random(5), 1 * 16 + 3
    names = [start, *(16 * k + 6 for k in range(9))]
    documents = {d: [] for d in names}
    for _ in range(60):
        triple = (rng.choice(names), rng.choice((4, 5, 6)), rng.choice([*names, start, start, 7777]))
        for d in rng.sample(names[:-1], 2):
            documents[d].append(triple)
    documents = {d: sorted(t) for d, t in documents.items()}
    q = query_from(q, start)
    rows = [(d, *t) for d, ts in documents.items() for t in ts or [(None, None, None)]]
    triples = spark.createDataFrame(rows, "doc long, s long, p int, o long")
    routings = [experiments.route(r, run) for r in ("uniform", "lr", "lr_li", "lr_mi", *(f"static_{'_'.join(map(str, x.order))}" for x in experiments.all_static(q))) for run in ((0, 1) if r == "uniform" else (0,))]
    assert all(counted.countable(q, APPROACHES["fifo"], r) for r in routings)
    got = counted.count(triples, spark.createDataFrame([(d,) for d in documents], "doc long"), q, routings)
    runs = [cell(SubWeb(documents), q, APPROACHES["fifo"], r) for r in routings]
    assert got["routed"] == [r.routed for r in runs]
    times = sorted(t for _, t, _ in runs[0].solutions)
    assert (got["n_docs"], got["attempted"], got["n_solutions"]) == (len(runs[0].trace), runs[0].attempted, len(times))
    assert (got["t_first"], got["t_half"], got["t_last"]) == ((times[0], times[(len(times) + 1) // 2 - 1], times[-1]) if times else (None, None, None))


def query_from(q, start):
    """The same query, begun at ``start`` whatever its constants are."""
    return type(q)(q.name, q.patterns, extra_seeds=(start,))


@pytest.mark.parametrize("n", [1, 64, 1000])
def test_draws_are_those_of_the_simulator(spark, n, monkeypatch):
    monkeypatch.setattr(counted, "CHUNK", 128)
    for seed in (0, 3):
        rng = Random(seed)
        words = [w for frame in counted._drawn(seed, n) for w in zip(frame["word"].tolist(), frame["bits"].tolist())]
        got = [bits >> k & 1 for _, bits in words for k in range(64)]
        assert [w for w, _ in words] == list(range(len(words))) and got[:n] == [rng.randrange(2) for _ in range(n)]


def test_what_rests_on_earlier_partials_is_not_counted():
    fifo, q1, q4 = APPROACHES["fifo"], WORKLOAD["q1"], WORKLOAD["q4"]
    assert all(counted.countable(q1, fifo, experiments.route(r, 0)) for r in experiments.routing_names("q1"))
    assert not counted.countable(q4, fifo, experiments.route("uniform", 0))
    assert not counted.countable(q1, APPROACHES["partial"], experiments.route("lr", 0))
    assert not counted.countable(query("open", ("?a", 4, "?b"), ("?a", 5, "?b"), ("?a", 6, "?b")), fifo, experiments.route("lr_mc_ls", 0))
