"""First come, first served needs one round for each level of the web, in the order of one lookup at a time."""

from webtraverse import queries
from webtraverse.plans import rounds
from webtraverse.plans.approaches import APPROACHES
from webtraverse.plans.query import WORKLOAD


def test_fifo_takes_the_whole_queue_in_the_same_order(spark, small):
    web = queries.web_of(spark, small)
    got = rounds.traverse(web, WORKLOAD["q2"], APPROACHES["fifo"], 1)
    levels = queries.reached_by(spark, small, "q2").agg({"depth": "max"}).first()[0] + 1
    assert got.rounds <= levels + 1
    alone = queries.QUERIES["trace_fifo_q2"](spark, small).orderBy("rank").collect()
    assert [r["doc"] for r in got.trace.orderBy("rank").collect()] == [r["doc"] for r in alone]
    assert got.solutions.count() == alone[-1]["solutions"]
