"""Cells of the grid: what a query asks for is all that is simulated, on all triples of the documents reached."""

from webtraverse import queries
from webtraverse.operators.reach import reach_ctes
from webtraverse.plans import experiments
from webtraverse.plans.query import WORKLOAD
from webtraverse.sources import basegraph, testweb


def test_a_query_of_one_approach_simulates_no_other(spark, small, monkeypatch):
    asked, run = [], experiments.run_cells
    monkeypatch.setattr(experiments, "run_cells", lambda web, reached, plans: asked.append(plans) or run(web, reached, plans))
    monkeypatch.setattr(queries, "_kept", {})
    queries.QUERIES["simulate_fifo_q2"](spark, small).collect()
    queries.QUERIES["grid_solution_counts_q2"](spark, small).collect()
    assert [{p[1] for p in plans} for plans in asked] == [{"fifo"}, {"partial_rel1"}]


def test_inputs_of_cells_are_the_reached_part_of_each_web(spark, small):
    import duckdb

    con = duckdb.connect()
    for t in basegraph.TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    webs = (testweb.WEBS[0], testweb.CORPUS_LIKE)
    web, reached = experiments.cell_inputs(spark, small, ("q2", "q4"), webs)
    for w in webs:
        docs, want = set(), {}
        for q in ("q2", "q4"):
            ctes = reach_ctes(WORKLOAD[q], testweb.web_sql(w), basegraph.ENTITY_SQL)
            want[q] = {r[0] for r in con.execute(f"{ctes} select doc from reached").fetchall()}
            docs |= want[q]
            assert {r["doc"] for r in reached.where((reached.web_id == w.web_id) & (reached["query"] == q)).collect()} == want[q]
        triples = sorted(r for r in con.execute(testweb.web_sql(w)).fetchall() if r[0] in docs)
        assert sorted(tuple(r) for r in web.where(web.web_id == w.web_id).select("doc", "s", "p", "o").collect()) == triples
