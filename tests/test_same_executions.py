"""Plans that are one and the same execution are simulated once, and each has its row."""

from webtraverse.plans import experiments
from webtraverse.plans.query import WORKLOAD
from webtraverse.plans.simulate import SubWeb, cell
from test_hubs import hub


def test_a_query_of_two_patterns_has_one_execution_for_all_routings():
    q, names = WORKLOAD["q2"], experiments.routing_names("q2")
    assert len({experiments.execution(q, "partial", r, 0) for r in names}) == 1
    web = hub(20)
    runs = [cell(web, q, experiments.APPROACHES["partial_rcc1"], experiments.route(r, 0)) for r in names]
    assert all((x.trace, x.solutions, x.routed, x.attempted) == (runs[0].trace, runs[0].solutions, runs[0].routed, runs[0].attempted) for x in runs)


def test_choices_at_run_time_and_draws_stay_apart():
    q = WORKLOAD["q1"]
    assert len({experiments.execution(q, "fifo", r, 0) for r in ("lr", "uniform", "lr_mi")}) >= 2
    assert experiments.execution(WORKLOAD["q2"], "random", "lr_mi", 0) != experiments.execution(WORKLOAD["q2"], "random", "lr_mi", 1)
    assert experiments.execution(q, "fifo", "uniform", 0) != experiments.execution(q, "fifo", "uniform", 1)
