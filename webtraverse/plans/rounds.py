"""Traversal of a web of any size in rounds: the best URIs of the queue are looked up together, a batch at a time.

With a batch of one this is the exact execution of ``simulate``; larger batches trade the freshness of priorities for fewer rounds. What is
reached and found does not depend on it; first come, first served takes the whole queue, which is the same order. All state is kept in tables of the shared folder: queue, seen URIs, links, indexed matches,
contributions, scores; the driver holds counts only. Each round narrows the web to the documents of its batch, joins new matches with older ones only, and
rescores the URIs that are still queued.

A round in tables costs some jobs however few documents it looks up. ``execute`` takes the rounds of a part of the web that one task can hold to one
task: what is reached is found by the cluster, then the same batches are looked up in the same order by ``simulate``.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.terms import URI, seeded
from ..operators import construct, linkgraph
from ..operators.reach import Web, links, matches, matching_triples, ranked, seed_frame
from ..operators.routing import Routing
from ..session import discard, durable, ship_package
from .approaches import Approach, Arrival, LinkGraph, Oracle, Partial
from .query import ConjunctiveQuery, Lit
from .simulate import Stop, SubWeb, cell, documents_of


@dataclass
class Outcome:
    trace: DataFrame  # doc, rank
    solutions: DataFrame  # variables, d0.., prov, t_avail
    rounds: int
    lookups: int
    attempted: int
    priority_changes: int
    seconds: list[float] = field(default_factory=list)


#: Tables of as many rounds are written as one, so that plans and listings don't grow with the number of rounds.
FOLD = 8

#: So many documents, and triples, are held by one task.
ONE_TASK_DOCUMENTS = 500_000
ONE_TASK_TRIPLES = 5_000_000


def _all(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _fold(parts: list[DataFrame], name: str) -> None:
    """Once there are ``FOLD`` tables they become one; their rows stay the same."""
    if len(parts) >= FOLD:
        parts[:] = [durable(_all(parts), name)]


class Traversal:
    def __init__(self, web: Web, query: ConjunctiveQuery, approach: Approach, batch: int = 1000, routing: Routing = Routing(), seed: int = 0, rcc: DataFrame | None = None, stop: Stop | None = None, keep_web: bool = False, seconds: float | None = None):
        self.web, self.query, self.approach, self.batch, self.routing, self.seed, self.stop, self.limit = web, query, approach, batch, routing, seed, stop, seconds
        self.spark = web.spark
        self.oracle = rcc
        # First come, first served: what a round finds comes after all that is queued, so the whole queue is one batch of the same order.
        self.whole = isinstance(approach, Arrival) and not approach.step and not approach.draw and stop is None and seconds is None
        if keep_web:  # a second execution then needs no lookup
            web.triples.persist()
        self.names = web.resolve.where("doc is not null").select("uri", "doc")
        self.trace: list[DataFrame] = []
        self.seen: list[DataFrame] = []
        self.found: list[DataFrame] = []
        self.edges: list[DataFrame] = []
        self.solutions: list[DataFrame] = []
        self.scores: DataFrame | None = None
        self.rank = self.arrivals = self.attempted = self.changes = self.n_solutions = 0

    # Priorities ------------------------------------------------------------------------------------------------------

    def _first(self, new: DataFrame) -> DataFrame:
        """Start values of new queue rows (uri, enq, parent_prio): ``base`` is what the approach gives before any feedback."""
        a = self.approach
        base = F.lit(0.0)
        if isinstance(a, Arrival) and a.draw:
            base = seeded(self.seed, F.col("uri"))
        elif isinstance(a, Arrival) and a.step:
            base = F.coalesce(F.col("parent_prio") + a.step, F.lit(0.0))
        elif isinstance(a, Partial) and a.inherit:
            base = F.coalesce(F.col("parent_prio") - 1, F.lit(0.0))
        return new.select("uri", "enq", base.cast("double").alias("base"))

    def _scored(self, queue: DataFrame) -> DataFrame:
        """(uri, enq, base, prio) with current priorities."""
        a = self.approach
        if isinstance(a, Arrival):
            return queue.withColumn("prio", F.col("base"))
        if isinstance(a, Oracle):
            return queue.join(self.oracle.select(F.col("doc").alias("uri"), "rcc"), "uri", "left").select("uri", "enq", "base", F.coalesce(F.col("rcc").cast("double"), F.lit(0.0)).alias("prio"))
        edges = _all(self.edges) if self.edges else None
        if isinstance(a, LinkGraph):
            if edges is None:
                return queue.withColumn("prio", F.col("base"))
            score = linkgraph.degrees(edges)[0].withColumnRenamed("indegree", "score") if a.name == "indegree" else linkgraph.pagerank(edges, a.damping, a.rounds, a.tolerance).withColumnRenamed("rank", "score")
            return queue.join(score, "uri", "left").select("uri", "enq", "base", F.coalesce(F.col("score").cast("double"), F.lit(0.0)).alias("prio"))
        out = queue
        if a.uses_partials:
            hits = self.scores if self.scores is not None else queue.select("uri", F.lit(0).alias("cnt")).limit(0)
            out = out.join(hits, "uri", "left").withColumn("is_score", F.greatest("base", F.coalesce(F.col("cnt").cast("double"), F.col("base")))).drop("cnt")
        if a.uses_solutions:
            if self.solutions and edges is not None:
                counts = linkgraph.rcc(_all(self.solutions))
                near = linkgraph.solution_scores(edges, counts, a.steps).select("uri", F.col(f"{a.measure}_score").alias("near"))
                out = out.join(near, "uri", "left").withColumn("near", F.coalesce("near", F.lit(0)))
            else:
                out = out.withColumn("near", F.lit(0))
        if isinstance(a, Partial):
            prio = F.col("is_score")
        elif a.family == "solution":
            prio = F.col("near").cast("double")
        else:
            prio = F.col("is_score") * (F.col("near") + (1 if a.combine == "smoothed" else 0))
        return out.select("uri", "enq", "base", prio.alias("prio"))

    # One round -------------------------------------------------------------------------------------------------------

    def _lookup(self, batch: DataFrame) -> DataFrame:
        """(doc, rank, prio) of the documents that this batch retrieves for the first time, in the order of the queue."""
        got = batch.join(self.names, "uri").groupBy("doc").agg(F.min(F.struct((-F.col("prio")).alias("first"), "enq")).alias("o"), F.max_by("prio", "prio").alias("prio"))
        if self.trace:
            got = got.join(_all(self.trace).select("doc"), "doc", "left_anti")
        if self.whole:
            return durable(ranked(got, "o").select("doc", (F.col("rank") + self.rank).cast("long").alias("rank"), "prio"), "batch")
        place = F.row_number().over(W.orderBy("o"))  # no more rows than the batch
        return durable(got.select("doc", (place + self.rank).cast("long").alias("rank"), "prio"), "batch")

    def _discover(self, docs: DataFrame, triples: DataFrame) -> DataFrame:
        """(uri, enq, parent_prio) of URIs never seen before, numbered in the order of documents and triples."""
        hits = matching_triples(triples, self.query).join(docs, "doc")
        uris = F.array(F.struct(F.lit(0).alias("pos"), F.col("s").alias("uri")), F.struct(F.lit(1).alias("pos"), (F.col("p").cast("long") * 16).alias("uri")), F.struct(F.lit(2).alias("pos"), F.when(F.col("o_kind") == 1, F.col("o")).alias("uri")))
        rows = hits.select("rank", "s", "p", "o", "prio", F.explode(uris).alias("u")).where("u.uri >= 0")
        firsts = rows.groupBy(F.col("u.uri").alias("uri")).agg(F.min(F.struct("rank", "s", "p", "o", "u.pos")).alias("o"), F.min_by("prio", F.struct("rank", "s", "p", "o", "u.pos")).alias("parent_prio"))
        new = ranked(firsts.join(_all(self.seen), "uri", "left_anti"), "o")
        return durable(new.select("uri", (F.col("rank") + self.arrivals).cast("long").alias("enq"), "parent_prio"), "new")

    def _construct(self, docs: DataFrame, triples: DataFrame) -> None:
        fresh = construct.stamped(matches(triples, self.query), docs)
        if not self.approach.uses_partials:
            fresh = durable(fresh, "matches")
            old = _all(self.found) if self.found else fresh.limit(0)
            ranks = [F.col(f"rank{i}") for i in range(self.query.n)]
            got = self._delta(fresh, old).withColumn("t_avail", F.greatest(*ranks) if len(ranks) > 1 else ranks[0]).drop(*[f"rank{i}" for i in range(self.query.n)])
        else:
            fresh = durable(self._sized(construct.asof_sizes(fresh, self.query)), "matches")
            index = _all([*self.found, fresh])
            done, routed = construct.hops(fresh, index, self.query, self.routing)
            ids = [f"d{i}" for i in range(self.query.n)]
            got = done.select(*self.query.variables, *ids, F.array_distinct(F.array(*ids)).alias("prov"), F.shiftright("ts", 24).alias("t_avail"))
            mentioned = [r.select("covered", F.explode(F.array(*self.query.variables)).alias("uri")).where("uri >= 0") for r in routed]
            if getattr(self.approach, "count_complete", False):
                mentioned.append(got.select(F.lit((1 << self.query.n) - 1).alias("covered"), F.explode(F.array(*self.query.variables)).alias("uri")))
            hits = _all(mentioned).groupBy("uri").agg(F.max(F.bit_count("covered")).alias("cnt"))
            if self.scores is not None:
                hits = self.scores.unionByName(hits).groupBy("uri").agg(F.max("cnt").alias("cnt"))
            self.scores = durable(hits, "scores")
        self.found.append(fresh)
        got = durable(got, "solutions")
        if not got.isEmpty():
            self.solutions.append(got)

    def _sized(self, fresh: DataFrame) -> DataFrame:
        """Index sizes of earlier rounds are added to those within the batch."""
        before = {r["pattern_id"]: r["n"] for r in _all(self.found).groupBy("pattern_id").agg(F.count("*").alias("n")).collect()} if self.found else {}
        base = F.array(*[F.lit(before.get(i, 0)).cast("long") for i in range(self.query.n)])
        return fresh.withColumn("sizes", F.zip_with("sizes", base, lambda a, b: a + b))

    def _delta(self, new: DataFrame, old: DataFrame) -> DataFrame:
        q, both, parts = self.query, old.unionByName(new), []
        for i in range(q.n):
            frames = [construct.pattern_frame(new if j == i else both if j < i else old, q, j, "rank") for j in range(q.n)]
            ids = [f"d{j}" for j in range(q.n)]
            parts.append(construct.join_all(frames, q, q.join_order(i)).select(*q.variables, *ids, F.array_distinct(F.array(*ids)).alias("prov"), *[f"rank{j}" for j in range(q.n)]))
        return _all(parts)

    def run(self) -> Outcome:
        start, began, clock = seed_frame(self.spark, self.query), time.time(), []
        start = start.select("uri", (F.col("seed_no") + 1).cast("long").alias("enq"), F.lit(None).cast("double").alias("parent_prio"))
        self.arrivals = len(self.query.seeds())
        self.seen.append(durable(start.select("uri"), "seen"))
        queue = durable(self._scored(self._first(start)), "queue")
        rounds = 0
        while not queue.isEmpty():
            if self.stop and ((self.stop.k is not None and self.n_solutions >= self.stop.k) or (self.stop.lookups is not None and self.rank >= self.stop.lookups)):
                break
            if self.limit is not None and time.time() - began > self.limit:
                break
            t = time.time()
            rounds += 1
            batch = queue if self.whole else durable(queue.orderBy(F.desc("prio"), "enq").limit(self.batch), "take")
            self.attempted += batch.count()
            waiting = (queue.limit(0) if self.whole else queue.join(batch.select("uri"), "uri", "left_anti")).withColumnRenamed("prio", "was")
            docs = self._lookup(batch)
            n_docs = docs.count()
            if n_docs:
                triples = durable(self.web.triples.join(docs.select("doc"), "doc"), "fetched")
                new = self._discover(docs, triples)
                self.seen.append(new.select("uri"))
                if isinstance(self.approach, LinkGraph) or self.approach.uses_solutions:
                    self.edges.append(durable(links(triples), "edges"))
                self._construct(docs, triples)
                self.arrivals += new.count()
                self.rank += n_docs
                self.trace.append(docs.select("doc", "rank"))
                if self.stop and self.stop.k is not None:
                    self.n_solutions = sum(s.count() for s in self.solutions)
                grown = waiting.select("uri", "enq", "base").unionByName(self._first(new))
            else:
                grown = waiting.select("uri", "enq", "base")
            after = durable(self._scored(grown), "queue")
            self.changes += after.join(waiting.select("uri", "was"), "uri").where("was <> prio").count() if self.approach.adaptive else 0
            discard(queue)
            queue = after
            for parts, name in ((self.seen, "seen"), (self.edges, "edges"), (self.found, "matches"), (self.solutions, "solutions"), (self.trace, "trace")):
                _fold(parts, name)
            clock.append(time.time() - t)
        q = self.query
        ids = ", ".join(f"d{i} long" for i in range(q.n))
        empty = lambda schema: self.spark.createDataFrame([], schema)
        found = _all(self.solutions) if self.solutions else empty(", ".join(f"{v} long" for v in q.variables) + f", {ids}, prov array<long>, t_avail long")
        return Outcome(_all(self.trace) if self.trace else empty("doc long, rank long"), found, rounds, self.rank, self.attempted, self.changes, clock)


def traverse(web: Web, query: ConjunctiveQuery, approach: Approach, batch: int = 1000, **options) -> Outcome:
    """Execute ``query``; an oracle without known contributions makes a dry run first, as it was first come, first served."""
    if isinstance(approach, Oracle) and options.get("rcc") is None:
        dry = traverse(web, query, Arrival("fifo"), batch)
        options["rcc"] = durable(linkgraph.rcc(dry.solutions), "rcc")
    return Traversal(web, query, approach, batch, **options).run()


def execute(web: Web, query: ConjunctiveQuery, approach: Approach, batch: int, reached: DataFrame) -> Outcome:
    """``traverse`` where ``reached`` (doc) is known: by one task if it can hold that part of the web, else in tables."""
    names = web.resolve.where("doc is not null")
    held = reached.select("doc").join(web.triples.select("doc", "s", "p", "o_kind", "o"), "doc", "left")
    if any(isinstance(x, Lit) for t in query.patterns for x in (t.s, t.p, t.o)) or not names.where("uri <> doc").isEmpty():
        return traverse(web, query, approach, batch)
    held = durable(held, "held")
    n_docs, n_triples, n_literals = held.agg(F.countDistinct("doc"), F.count("s"), F.count_if(F.col("o_kind") != URI)).first()
    if n_docs > ONE_TASK_DOCUMENTS or n_triples > ONE_TASK_TRIPLES or n_literals:
        return traverse(web, query, approach, batch)
    return one_task(held, query, approach, batch)


def one_task(held: DataFrame, query: ConjunctiveQuery, approach: Approach, batch: int) -> Outcome:
    """All rounds over the documents of ``held`` (doc, s, p, o); a document without triples has one row of nulls."""
    began = time.time()
    ship_package(held.sparkSession)

    def simulate(frame: pd.DataFrame) -> pd.DataFrame:
        got = cell(SubWeb(documents_of(frame)), query, approach, batch=batch)
        rows = [("run", None, None, [got.rounds, len(got.trace), got.attempted, got.priority_changes])]
        rows += [("doc", rank, doc, None) for rank, doc in enumerate(got.trace, 1)]
        rows += [("solution", t, None, [*values, *docs]) for values, t, docs in got.solutions]
        return pd.DataFrame(rows, columns=["kind", "t", "doc", "ids"]).astype({"t": "Int64", "doc": "Int64"})

    out = durable(held.select("doc", "s", "p", "o").groupBy().applyInPandas(simulate, "kind string, t long, doc long, ids array<long>"), "onetask")
    counts = out.where("kind = 'run'").first()
    n, ids = len(query.variables), [f"d{i}" for i in range(query.n)]
    cells = [F.col("ids")[i].alias(name) for i, name in enumerate([*query.variables, *ids])]
    found = out.where("kind = 'solution'").select(*cells, F.array_distinct(F.slice("ids", n + 1, query.n)).alias("prov"), F.col("t").alias("t_avail"))
    trace = out.where("kind = 'doc'").select("doc", F.col("t").alias("rank"))
    return Outcome(trace, found, *(counts["ids"] if counts else (0, 0, 0, 0)), [time.time() - began])
