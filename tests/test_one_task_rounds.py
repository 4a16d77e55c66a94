"""Rounds taken by one task equal the rounds in tables."""

import pytest

from webtraverse import queries
from webtraverse.plans import rounds
from webtraverse.plans.approaches import APPROACHES
from webtraverse.plans.query import WORKLOAD


@pytest.mark.parametrize("name", ["indegree", "partial_rcc1"])
def test_one_task_takes_the_rounds_that_tables_take(spark, small, name, monkeypatch):
    web, q = queries.web_of(spark, small), WORKLOAD["q2"]
    reached = queries.reached_by(spark, small, "q2")
    batch = max(2, reached.count() // 3)
    tables = rounds.traverse(web, q, APPROACHES[name], batch)
    monkeypatch.setattr(rounds, "traverse", None)
    one = rounds.execute(web, q, APPROACHES[name], batch, reached)
    assert sorted(one.solutions.collect()) == sorted(tables.solutions.collect())
    order = [[r["doc"] for r in x.trace.orderBy("rank").collect()] for x in (one, tables)]
    assert order[0] == order[1]
    assert (one.lookups, one.attempted) == (tables.lookups, tables.attempted)


def test_a_part_of_the_web_too_large_for_a_task_stays_in_tables(spark, small, monkeypatch):
    web, q = queries.web_of(spark, small), WORKLOAD["q2"]
    monkeypatch.setattr(rounds, "ONE_TASK_DOCUMENTS", 3)
    monkeypatch.setattr(rounds, "traverse", lambda *args: "tables")
    assert rounds.execute(web, q, APPROACHES["rel1"], 64, queries.reached_by(spark, small, "q2")) == "tables"
