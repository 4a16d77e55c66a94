"""A traversal goes on until nothing is new, however deep the web is."""

from webtraverse.operators import reach
from webtraverse.operators.reach import Web
from webtraverse.plans.query import query


def test_reach_has_no_greatest_depth(spark):
    q = query("deep", ("customer:1", "o_cust", "?x"))
    start, = q.seeds()[:1]
    chain = [start, *(1_000_000 + i for i in range(1, 20))]
    rows = [(a, chain[0], 4, 1, b) for a, b in zip(chain, chain[1:])]
    triples = spark.createDataFrame(rows, "doc long, s long, p int, o_kind int, o long")
    names = spark.createDataFrame([(c, c) for c in chain], "uri long, doc long")
    got = {r["doc"]: r["depth"] for r in reach.reach(Web(triples, names), q).collect()}
    assert got == {c: i for i, c in enumerate(chain)}
