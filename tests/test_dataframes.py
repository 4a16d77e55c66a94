"""DataFrame operators against the simulator and against each other; plans; streams."""

import random

import pytest
from pyspark.sql import functions as F

from webtraverse import queries as Q
from webtraverse.functions.terms import place_draws
from webtraverse.operators import construct, linkgraph, metrics, reach
from webtraverse.operators.reach import Web
from webtraverse.operators.routing import Routing
from webtraverse.plans import experiments
from webtraverse.plans.approaches import APPROACHES
from webtraverse.plans.query import WORKLOAD
from webtraverse.plans.rounds import traverse
from webtraverse.plans.simulate import Stop, SubWeb, cell
from webtraverse.sources import basegraph, pages_web, testweb
from webtraverse.streaming import solutions as streamed
from webtraverse.streaming import windows

from test_simulator import CHAIN, DOCS, WEB

TRIPLE = "doc long, s long, p int, o_kind byte, o long, o_str string, o_dbl double"


def web_frame(spark, docs):
    rows = [(d, s, p, 1, o, None, None) for d, ts in docs.items() for s, p, o in ts]
    return Web(spark.createDataFrame(rows, TRIPLE).coalesce(1), spark.createDataFrame([(d, d) for d in docs], "uri long, doc long").coalesce(1))


@pytest.mark.parametrize("name", ["fifo", "partial_rel1"])
def test_rounds_of_one_are_the_simulation(spark, name):
    got = traverse(web_frame(spark, DOCS), CHAIN, APPROACHES[name], batch=1)
    run = cell(WEB, CHAIN, APPROACHES[name])
    assert [r["doc"] for r in got.trace.orderBy("rank").collect()] == run.trace
    rows = sorted((r["x"], r["y"], r["z"], r["t_avail"]) for r in got.solutions.collect())
    assert rows == sorted((*s, t) for s, t, _ in run.solutions)


@pytest.mark.parametrize("name", ["rcc2", "partial_decay", "indegree", "oracle_rcc"])
def test_batches_change_order_only(spark, name):
    got = traverse(web_frame(spark, DOCS), CHAIN, APPROACHES[name], batch=4)
    assert sorted(r["doc"] for r in got.trace.collect()) == sorted(DOCS) and got.lookups == 9
    assert sorted((r["x"], r["y"], r["z"]) for r in got.solutions.collect()) == [(2, 5, 7), (3, 6, 8), (3, 6, 8)]


def test_stop_gives_a_prefix(spark):
    got = traverse(web_frame(spark, DOCS), CHAIN, APPROACHES["breadth_first"], batch=3, stop=Stop(lookups=5))
    assert 5 <= got.lookups < 9


def test_hops_route_what_the_simulator_routes(spark):
    web = web_frame(spark, DOCS)
    order = cell(WEB, CHAIN, APPROACHES["fifo"]).trace
    trace = spark.createDataFrame([(d, i + 1) for i, d in enumerate(order)], "doc long, rank long")
    found = construct.asof_sizes(construct.stamped(reach.matches(web.triples, CHAIN), trace), CHAIN, bucket=2).cache()
    done, routed = construct.hops(found, found, CHAIN, Routing("lr_mi"))
    assert sum(r["n_routed"] for r in construct.routed_stats(routed).collect()) == 17
    assert sorted((r["x"], r["y"], r["z"], r["ts"] >> 24) for r in done.collect()) == [(2, 5, 7, 5), (3, 6, 8, 6), (3, 6, 8, 8)]


def test_reach_conditions_are_nested(spark):
    web = web_frame(spark, DOCS)
    none, some, all_ = ({r["doc"] for r in reach.reach(web, CHAIN, f).collect()} for f in ("none", "match", "all"))
    assert none == {1} and none <= some <= all_ and some == set(DOCS)
    assert {r["uri"] for r in reach.failed_lookups(web, CHAIN, reach.reach(web, CHAIN)).collect()} == {10, 160, 176, 192}


def test_sets_and_bags(spark):
    web = web_frame(spark, DOCS)
    found = reach.matches(web.triples, CHAIN)
    assert construct.solutions(found, CHAIN).count() == 3 and construct.solutions(construct.distinct_matches(found), CHAIN).count() == 2
    assert tuple(construct.bag_count(found, CHAIN).first()) == (3, 2)
    assert construct.full_web(web.triples, CHAIN).count() == 2
    parts = [construct.delta(found.where("doc > 5"), found.where("doc <= 5"), CHAIN), construct.delta(found.where("doc <= 5"), found.limit(0), CHAIN)]
    assert sum(p.count() for p in parts) == 3


def test_link_graph(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 4), (6, 1)], "src long, dst long")
    vertices = spark.createDataFrame([(i,) for i in range(1, 8)], "v long")
    groups = {}
    for r in linkgraph.strong_components(vertices, edges).collect():
        groups.setdefault(r["component"], set()).add(r["v"])
    assert sorted(map(sorted, groups.values())) == [[1, 2, 3], [4, 5], [6], [7]]
    assert linkgraph.diameter(vertices, edges) == 5
    rank = {r["uri"]: r["rank"] for r in linkgraph.pagerank(edges, rounds=60, tolerance=1e-12).collect()}
    assert abs(sum(rank.values()) - 1) < 1e-6 and rank[4] == max(rank.values())
    counts = spark.createDataFrame([(1, 3), (3, 2)], "doc long, rcc long")
    two = {r["uri"]: (r["rcc_score"], r["rel_score"]) for r in linkgraph.solution_scores(edges, counts, 2).collect()}
    assert two == {1: (2, 1), 2: (5, 2), 3: (3, 1), 4: (2, 1), 5: (2, 1)}


def test_worse_and_better(spark):
    rows = [("w", "a", "fifo", 0.5, 0.5, 0.5), ("w", "a", "x", 0.55, 0.45, 0.51), ("v", "a", "fifo", 0.2, 0.4, 1.0), ("v", "a", "x", 0.1, 0.5, 0.9)]
    frame = spark.createDataFrame(rows, "web_id string, query string, approach string, relRT1st double, relRT50 double, relRTCmpl double")
    got = {r["measure"]: (r["n_cells"], r["n_worse"], r["n_better"], r["pct_worse"]) for r in metrics.compare_to_baseline(frame).collect()}
    assert got == {"relRT1st": (2, 1, 1, 50.0), "relRT50": (2, 1, 1, 50.0), "relRTCmpl": (2, 0, 1, 0.0)}
    assert metrics.retrieval_model(100, 8, 0.5) == 6.5


def test_placement(spark, small):
    base = basegraph.triples(spark, small, literals=False)
    counts = {r["side"]: r["count"] for r in base.withColumn("u1", place_draws(F.col("s"), F.col("p"), F.col("o"), 42)[0]).withColumn("u2", place_draws(F.col("s"), F.col("p"), F.col("o"), 42)[1]).groupBy(F.when(F.col("u1") < 0.62, "both").when(F.col("u2") < 0.47, "subject").otherwise("object").alias("side")).count().collect()}
    assert counts == {"both": 11265, "subject": 3257, "object": 3793}
    full, none = testweb.place(base, testweb.WEBS[12]), testweb.place(base, testweb.WEBS[0])
    assert full.count() == 2 * base.count() and none.count() == base.count()
    phi = testweb.estimate_phi(testweb.place(base)).first()
    assert abs(phi["phi1"] - 0.62) < 0.02 and abs(phi["phi2"] - 0.47) < 0.02


@pytest.mark.parametrize("name,docs,bag,set_", [("q2", 41, 108, 35), ("q1", 6024, 188, 49), ("q3", 22, 0, 0)])
def test_workload_counts(spark, small, name, docs, bag, set_):
    assert Q.reached_by(spark, small, name).count() == docs
    assert tuple(construct.bag_count(Q.matches_of(spark, small, name), WORKLOAD[name]).first()) == (bag, set_)


def test_grid_cell_equals_operators(spark, small):
    got = experiments.grid(spark, small, ("q2",), (testweb.CORPUS_LIKE,), ("fifo", "rel1", "partial_rel1")).collect()
    assert all((r["n_docs"], r["n_solutions"]) == (41, 108) for r in got)
    by = {r["approach"]: r for r in got}
    assert by["rel1"]["t_first"] == by["fifo"]["t_first"] and by["partial_rel1"]["t_first"] <= by["fifo"]["t_first"]


def test_plans_push_filters_and_avoid_products(spark, small):
    web = Q.web_of(spark, small)
    plan = reach.matches(web.triples, WORKLOAD["q1"])._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [Or" in plan and "Python" not in plan
    plan = construct.solutions(Q.matches_of(spark, small, "q4"), WORKLOAD["q4"])._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan


def test_ntriples(spark):
    lines = ['<http://a> <http://p> <http://b> .', '<http://a> <http://p> "x \\" y"@en .', '_:n <http://p> _:n .', "junk", '<http://b> <http://p> "5"^^<http://int> .']
    rows = pages_web.parse_ntriples(spark.createDataFrame([(x,) for x in lines], "value string")).collect()
    assert [r["o_kind"] for r in rows] == [1, 2, 3, 2] and rows[2]["s"] == rows[2]["o"] < 0 < rows[0]["o"] == rows[3]["s"] and rows[3]["o_str"] == "5"


def test_streams_equal_batches(spark, small, tmp_path):
    events = spark.read.parquet(f"{small}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    late = events.where("event_id % 97 = 0").withColumn("ts", F.col("ts") - F.expr("interval 2 hours"))
    events.unionByName(late).orderBy("ts").write.parquet(str(tmp_path / "events"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "events"))
    for name, make in (("tumbling", windows.tumbling), ("sliding", windows.sliding), ("sessions", windows.sessions)):
        query = make(stream).writeStream.format("memory").queryName(name).outputMode("complete" if name != "sessions" else "append").start()
        query.processAllAvailable()
        query.stop()
        expected = {tuple(r) for r in make(events.unionByName(late)).collect()}
        got = {tuple(r) for r in spark.table(name).collect()}
        assert got and (got == expected if name != "sessions" else got <= expected)


def test_streamed_solutions(spark, tmp_path):
    web = web_frame(spark, DOCS)
    order = list(DOCS)
    random.Random(2).shuffle(order)
    trace = spark.createDataFrame([(d, i + 1) for i, d in enumerate(order)], "doc long, rank long")
    found = reach.matches(web.triples, CHAIN).join(trace, "doc").select("rank", "pattern_id", "doc", *CHAIN.variables).orderBy("rank")
    rows = found.collect()
    for i in range(3):
        spark.createDataFrame(rows[i::3], found.schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "m"))
    stream = spark.readStream.schema(found.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "m"))
    query = streamed.network(stream, CHAIN).writeStream.format("memory").queryName("sols").outputMode("append").start()
    query.processAllAvailable()
    query.stop()
    got = sorted((r["x"], r["y"], r["z"], r["rank"]) for r in spark.table("sols").collect())
    place = {d: i + 1 for i, d in enumerate(order)}
    assert got == sorted([(2, 5, 7, max(place[d] for d in (1, 2, 5))), (3, 6, 8, max(place[d] for d in (1, 3, 6))), (3, 6, 8, max(place[d] for d in (1, 3, 8)))])


def test_stream_join_of_two_patterns(spark, small, tmp_path):
    q = WORKLOAD["q2"]
    found = Q.matches_of(spark, small, "q2").join(Q.trace_of(spark, small, "q2").select("doc", "rank"), "doc")
    found = found.select(F.timestamp_seconds("rank").alias("arrival"), "pattern_id", "doc", *q.variables)
    found.write.parquet(str(tmp_path / "m"))
    stream = spark.readStream.schema(found.schema).parquet(str(tmp_path / "m"))
    query = streamed.pairs(stream, q).writeStream.format("memory").queryName("pairs").start()
    query.processAllAvailable()
    query.stop()
    assert spark.table("pairs").count() == 108


def test_no_machine_local_folder_on_a_cluster(spark):
    from types import SimpleNamespace

    from webtraverse.session import shared_dir

    settings = SimpleNamespace(get=lambda key, default=None: None)
    session = lambda master: SimpleNamespace(conf=settings, sparkContext=SimpleNamespace(master=master, getConf=lambda: settings))
    assert shared_dir(session("local[4]")).startswith("file://")
    with pytest.raises(RuntimeError, match="checkpoint.dir"):
        shared_dir(session("spark://host:7077"))
