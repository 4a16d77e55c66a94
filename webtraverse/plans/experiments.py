"""The grid of experiments: web x query x approach x run, spread over the cluster by cell."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.terms import URI
from ..operators.reach import links, matching_triples
from ..operators.routing import POLICIES, Routing, all_static
from ..session import discard, durable, ship_package
from ..sources import basegraph, testweb
from . import counted
from .approaches import APPROACHES, LITERAL_HYBRIDS, Arrival
from .packed import PackedWeb
from .query import WORKLOAD, ConjunctiveQuery
from .simulate import SubWeb, cell, documents_of, response_times

MOST_DOCUMENTS = 2_000_000
#: From so many lookups on, over all executions of a cell, plans that tables can count are not simulated.
MOST_LOOKUPS = 500_000
#: A subweb is sent to at most so many tasks, each of which runs its share of the plans over it.
LANES = 4
RESULT = (
    "web_id string, query string, approach string, routing string, run int, n_docs long, n_solutions long, t_first long, t_half long, t_last long, "
    "relRT1st double, relRT50 double, relRTCmpl double, routed long, priority_changes long, attempted long"
)


ARROW = {"string": "string", "int": "int32", "long": "int64", "double": "float64"}


def reach_cells(web: DataFrame, names: DataFrame, queries: list[ConjunctiveQuery], web_ids: list[str] | None = None) -> DataFrame:
    """(web_id, query, doc): what each query reaches in each web, all cells in one loop. With ``web_ids`` given, matching triples alone will do."""
    spark = web.sparkSession
    edges = []
    for q in queries:
        per = matching_triples(web, q)
        uris = F.array_distinct(F.concat(F.array("s"), F.when(F.col("o_kind") == URI, F.array("o")).otherwise(F.array().cast("array<bigint>"))))
        edges.append(per.select("web_id", F.lit(q.name).alias("query"), F.col("doc").alias("src"), F.explode(uris).alias("dst")).where("src <> dst").distinct())
    # Links that lead nowhere are left out once, so that no round looks at all names.
    edges = durable(reduce(DataFrame.unionByName, edges).join(names.select(F.col("uri").alias("dst"), "doc"), "dst").select("web_id", "query", "src", "doc"), "celledges")
    webs = web.select("web_id").distinct() if web_ids is None else spark.createDataFrame([(w,) for w in web_ids], "web_id string")
    seeds = spark.createDataFrame([(q.name, u) for q in queries for u in q.seeds()], "query string, uri long").join(names, "uri").select("query", "doc").distinct()
    found = [durable(webs.join(seeds).select("web_id", "query", "doc"), "cells")]
    while True:
        seen = reduce(DataFrame.unionByName, found)
        new = edges.join(found[-1].select("web_id", "query", F.col("doc").alias("src")), ["web_id", "query", "src"]).select("web_id", "query", edges["doc"]).distinct()
        new = durable(new.join(seen, ["web_id", "query", "doc"], "left_anti"), "cells")
        if new.isEmpty():
            discard(new)
            return seen
        found.append(new)


def route(routing: str, run: int) -> Routing:
    return Routing.static(map(int, routing[7:].split("_"))) if routing.startswith("static_") else Routing(routing, seed=run if routing == "uniform" else None)


def execution(query: ConjunctiveQuery, approach: str, routing: str, run: int) -> tuple:
    """Equal for plans that are the same execution: a routing that never has a choice at run time is its table of next operators."""
    policy = route(routing, run)
    table = tuple(tuple(policy.fixed_choice(query, mask)) for mask in range(1, (1 << query.n) - 1))
    free = any(len(among) > 1 for among in table)
    a = (APPROACHES | LITERAL_HYBRIDS)[approach]
    return approach, run if isinstance(a, Arrival) and a.draw else None, (routing, run) if free else table


def run_cells(web: DataFrame, reached: DataFrame, plans: list[tuple[str, str, str, int]]) -> DataFrame:
    """Simulate ``plans`` (query, approach, routing, run) on each web; a task holds one subweb and runs a share of the plans over it, one after another.

    A large cell is counted in tables, if all of its plans can be.
    """
    spark = web.sparkSession
    ship_package(spark)
    schema = pa.schema([(c.split()[0], getattr(pa, ARROW[c.split()[1]])()) for c in RESULT.split(", ")])
    names = schema.names
    alike: dict[str, dict[tuple, list]] = {}
    for name, *plan in plans:
        alike.setdefault(name, {}).setdefault(execution(WORKLOAD[name], *plan), []).append(tuple(plan))
    shares = {(name, i): list(of.values())[i :: min(LANES, len(of))] for name, of in alike.items() for i in range(min(LANES, len(of)))}
    sizes = reached.groupBy("web_id", "query").agg(F.count("*").alias("n")).collect()
    known = APPROACHES | LITERAL_HYBRIDS
    large = [x for x in sizes if x["n"] * len(alike.get(x["query"], ())) > MOST_LOOKUPS and all(counted.countable(WORKLOAD[x["query"]], known[of[0][0]], route(*of[0][1:])) for of in alike[x["query"]].values())]
    sizes = [x for x in sizes if x not in large]
    too_large = [x for x in sizes if x["n"] > MOST_DOCUMENTS]
    if too_large:
        raise ValueError(f"{too_large[0]} is too large for a cell; take plans.rounds")
    in_tables = []
    for x in large:
        of, here = alike[x["query"]], (F.col("web_id") == x["web_id"]) & (F.col("query") == x["query"])
        got = counted.count(web.where(F.col("web_id") == x["web_id"]), reached.where(here), WORKLOAD[x["query"]], [route(*same[0][1:]) for same in of.values()])
        figures = [got[c] for c in ("n_docs", "n_solutions", "t_first", "t_half", "t_last", "relRT1st", "relRT50", "relRTCmpl")]
        in_tables += [(x["web_id"], x["query"], *plan, *figures, routed, 0, got["attempted"]) for routed, same in zip(got["routed"], of.values()) for plan in same]
        reached = reached.where(~here)
    in_tables = spark.createDataFrame(in_tables, RESULT)
    if large and not sizes:
        return in_tables
    tasks = [(x["web_id"], *share) for x in sizes for share in sorted(shares) if share[0] == x["query"]]
    asked = spark.createDataFrame([(i, *task) for i, task in enumerate(tasks)], "task int, web_id string, query string, lane int")
    held = reached.join(web.select("web_id", "doc", "s", "p", "o"), ["web_id", "doc"], "left")
    # Many more partitions than groups: hardly two of them share a task, and free cores take the next one.
    rows = held.join(F.broadcast(asked), ["web_id", "query"]).select("task", "doc", "s", "p", "o").repartition(max(64, 8 * len(tasks)), "task")

    def simulate(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        web_id, name, lane = tasks[key[0].as_py()]
        held = PackedWeb.of_batches(batches)
        for same in shares[name, lane]:
            approach, routing, run = same[0]
            got = cell(held, WORKLOAD[name], known[approach], route(routing, run), seed=int(run), keep=False)
            times = sorted(got.times)
            rt = response_times(got)
            three = (times[0], times[(len(times) + 1) // 2 - 1], times[-1]) if times else (None, None, None)
            ratios = (rt["relRT1st"], rt["relRT50"], rt["relRTCmpl"]) if rt else (None, None, None)
            figures = (len(got.trace), len(times), *three, *ratios, got.routed, got.priority_changes, got.attempted)
            del got, times
            yield pa.RecordBatch.from_pylist([dict(zip(names, (web_id, name, *plan, *figures))) for plan in same], schema)

    simulated = rows.groupBy("task").applyInArrow(simulate, RESULT)
    return simulated.unionByName(in_tables) if large else simulated


def cell_inputs(spark: SparkSession, sf_dir: str, queries=("q2",), webs=testweb.WEBS) -> tuple[DataFrame, DataFrame]:
    """(web, reached) of the cells: the loop follows matching triples only, and of a web only the documents that it reaches are written."""
    wanted = [WORKLOAD[q] for q in queries]
    base = basegraph.triples(spark, sf_dir, literals=False)
    names = basegraph.entities(spark, sf_dir).select("uri", F.col("uri").alias("doc"))
    hits = reduce(DataFrame.unionByName, [matching_triples(base, q) for q in wanted])
    near = durable(testweb.all_webs(hits, webs).select("web_id", "doc", "s", "p", "o_kind", "o").distinct(), "hits")
    reached = durable(reach_cells(near, names, wanted, [w.web_id for w in webs]), "reached")
    docs = reached.select("web_id", "doc").distinct()
    ends = docs.select("doc").distinct()
    around = [base.select("s", "p", "o_kind", "o").join(ends.withColumnRenamed("doc", end), end, "left_semi") for end in ("s", "o")]
    held = reduce(DataFrame.unionByName, around).distinct()
    for c, kind in (("o_str", "string"), ("o_dbl", "double"), ("o_ts", "timestamp_ntz")):
        held = held.withColumn(c, F.lit(None).cast(kind))
    return durable(testweb.all_webs(held, webs).select("web_id", "doc", "s", "p", "o").join(docs, ["web_id", "doc"], "left_semi"), "webs"), reached


def grid(spark: SparkSession, sf_dir: str, queries=("q2",), webs=testweb.WEBS, approaches=tuple(APPROACHES), routings=("lr_mi",), runs: int = 1, given: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """One row for each (web, query, approach, routing, run). Only random orders and draws differ between runs. ``given`` are ``cell_inputs`` of these queries and webs."""
    web, reached = given or cell_inputs(spark, sf_dir, queries, webs)
    plans = []
    for q in queries:
        for a in approaches:
            for r in routings:
                varies = (isinstance(APPROACHES.get(a), Arrival) and APPROACHES[a].draw) or r == "uniform"
                plans += [(q, a, r, i) for i in range(runs if varies else 1)]
    return run_cells(web, reached, plans)


TRACE = "web_id string, query string, approach string, rank long, doc long, solutions long"


def traces(web: DataFrame, reached: DataFrame, query: str, approaches) -> DataFrame:
    """(web_id, query, approach, rank, doc, solutions): the order of lookups, and how many solutions exist after each."""
    ship_package(web.sparkSession)
    approaches = tuple(approaches)
    lanes = min(LANES, len(approaches))
    asked = web.sparkSession.createDataFrame([(i,) for i in range(lanes)], "lane int")
    held = reached.where(F.col("query") == query).join(web.select("web_id", "doc", "s", "p", "o"), ["web_id", "doc"], "left").join(F.broadcast(asked))

    def follow(key, frame: pd.DataFrame) -> pd.DataFrame:
        web_id, lane = key
        held, out = SubWeb(documents_of(frame)), []
        for approach in approaches[lane::lanes]:
            got = cell(held, WORKLOAD[query], (APPROACHES | LITERAL_HYBRIDS)[approach])
            times = pd.Series([t for _, t, _ in got.solutions], dtype="int64").value_counts()
            ranks = range(1, len(got.trace) + 1)
            out.append(pd.DataFrame({"web_id": web_id, "query": query, "approach": approach, "rank": list(ranks), "doc": got.trace, "solutions": times.reindex(ranks, fill_value=0).cumsum().tolist()}))
        return pd.concat(out)

    return held.groupBy("web_id", "lane").applyInPandas(follow, TRACE)


def routing_names(query: str, static: bool = True) -> tuple[str, ...]:
    """All policies and, for one query, all left-deep plans."""
    plans = ["static_" + "_".join(map(str, r.order)) for r in all_static(WORKLOAD[query])] if static else []
    return (*POLICIES, *plans)


def overhead(seconds: dict[str, float], of: str) -> dict[str, float]:
    """Time of one approach as a share of each of the others."""
    return {k: round(seconds[of] / v, 3) for k, v in seconds.items() if k != of and v}


__all__ = ["grid", "links", "overhead", "reach_cells", "routing_names", "run_cells"]
