"""Matching triples, and the documents that a traversal reaches under a condition.

A traversal is a loop over frontiers: each round is one join of the new documents with the links they may follow and one
anti-join with what has been seen; both shuffle on the URI. Only the count of a round reaches the driver.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.terms import URI
from ..plans.query import ConjunctiveQuery
from ..session import discard, durable


@dataclass
class Web:
    """``triples`` (doc, s, p, o_kind, o, ...) and ``resolve`` (uri, doc; doc is null where a lookup fails)."""

    triples: DataFrame
    resolve: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.triples.sparkSession


def matches(triples: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    """(pattern_id, doc, _s, _p, _o, variables...): a triple that matches k patterns gives k rows. One scan."""
    names = query.variables
    hits = []
    for i, pattern in enumerate(query.patterns):
        bound = dict(zip(pattern.places(), pattern.bindings()))
        values = [(bound[v] if v in bound else F.lit(None).cast("long").alias(v)) for v in names]
        hits.append(F.when(pattern.condition(), F.struct(F.lit(i).alias("pattern_id"), *values)))
    tests = [p.condition() for p in query.patterns]
    any_hit = tests[0]
    for t in tests[1:]:
        any_hit = any_hit | t
    cols = ["doc", "_s", "_p", "_o"]
    tagged = triples.where(any_hit).select("doc", F.col("s").alias("_s"), F.col("p").alias("_p"), F.col("o").alias("_o"), F.explode(F.filter(F.array(*hits), lambda x: x.isNotNull())).alias("m"))
    return tagged.select("m.pattern_id", *cols, *[F.col(f"m.{v}").alias(v) for v in names])


def matching_triples(triples: DataFrame, query: ConjunctiveQuery) -> DataFrame:
    any_hit = query.patterns[0].condition()
    for p in query.patterns[1:]:
        any_hit = any_hit | p.condition()
    return triples.where(any_hit)


def links(triples: DataFrame) -> DataFrame:
    """(src, dst), distinct: every URI that occurs in a triple of a document, but the document's own."""
    uris = F.array_distinct(F.concat(F.array("s", F.col("p").cast("long") * 16), F.when(F.col("o_kind") == URI, F.array("o")).otherwise(F.array().cast("array<bigint>"))))
    return triples.select(F.col("doc").alias("src"), F.explode(uris).alias("dst")).where("src <> dst").distinct()


def follow_edges(web: Web, query: ConjunctiveQuery, follow: str | Callable[[ConjunctiveQuery], Column] = "match") -> DataFrame:
    """Links that the condition allows: of matching triples, of all, of none, or of triples for which a given column holds."""
    if callable(follow):
        return links(web.triples.where(follow(query)))
    if follow == "match":
        return links(matching_triples(web.triples, query))
    if follow == "all":
        return links(web.triples)
    if follow == "none":
        return links(web.triples.where(F.lit(False)))
    raise ValueError(follow)


def seed_frame(spark: SparkSession, query: ConjunctiveQuery) -> DataFrame:
    return spark.createDataFrame([(u, i) for i, u in enumerate(query.seeds())], "uri long, seed_no int")


def reach(web: Web, query: ConjunctiveQuery, follow="match", limit: int | None = None) -> DataFrame:
    """(doc, depth, parent): reachable documents with their distance from the seeds; ``limit`` bounds the rounds."""
    spark = web.spark
    edges = durable(follow_edges(web, query, follow), "edges")
    names = web.resolve.where("doc is not null").select("uri", "doc")
    start = seed_frame(spark, query).join(names, "uri").select("doc").distinct()
    found = [durable(start.select("doc", F.lit(0).alias("depth"), F.lit(None).cast("long").alias("parent")), "reach")]
    depth = 0
    while limit is None or depth < limit:
        depth += 1
        seen = found[0]
        for f in found[1:]:
            seen = seen.unionByName(f)
        last = found[-1].select(F.col("doc").alias("src"))
        new = edges.join(last, "src").groupBy(F.col("dst").alias("uri")).agg(F.min("src").alias("parent")).join(names, "uri").groupBy("doc").agg(F.min("parent").alias("parent"))
        new = durable(new.join(seen.select("doc"), "doc", "left_anti").select("doc", F.lit(depth).alias("depth"), "parent"), "reach")
        if new.isEmpty():
            discard(new)
            break
        found.append(new)
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out


def failed_lookups(web: Web, query: ConjunctiveQuery, reached: DataFrame) -> DataFrame:
    """(uri): URIs that the traversal met but that lead nowhere."""
    met = follow_edges(web, query).join(reached.select(F.col("doc").alias("src")), "src").select(F.col("dst").alias("uri"))
    met = met.unionByName(seed_frame(web.spark, query).select("uri")).distinct()
    return met.join(web.resolve.where("doc is not null"), "uri", "left_anti")


def ranked(df: DataFrame, *order: str) -> DataFrame:
    """``df`` with ``rank`` (from 1) in the given order: a distributed sort, then offsets of its partitions; no single task sees all rows."""
    sorted_ = durable(df.orderBy(*order).withColumn("_at", F.monotonically_increasing_id()), "sorted")
    part = F.shiftright("_at", 33).alias("part")
    sizes = sorted_.groupBy(part).agg(F.count("*").alias("n"))
    earlier = W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)  # one row for each partition of the sort
    sums = sizes.select("part", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))
    return sorted_.withColumn("part", F.shiftright("_at", 33)).join(F.broadcast(sums), "part").withColumn("rank", F.col("before") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1)) + 1).drop("_at", "part", "before")


def canonical_trace(reached: DataFrame) -> DataFrame:
    """(doc, rank): a breadth-first order with ties by id instead of arrival."""
    return ranked(reached.select("doc", "depth"), "depth", "doc").select("doc", "depth", "rank")


# SQL twins ----------------------------------------------------------------------------------------------------------


def condition_sql(query: ConjunctiveQuery) -> str:
    parts = []
    for t in query.patterns:
        tests = [f"{c} = {x}" for c, x in (("s", t.s), ("p", t.p), ("o", t.o)) if isinstance(x, int)]
        parts.append("(" + (" and ".join(tests) or "true") + ")")
    return " or ".join(parts)


def reach_ctes(query: ConjunctiveQuery, web_sql: str, entity_sql: str, follow: str = "match", bound: int = 14) -> str:
    """``with recursive`` text that defines web, entities, reached (doc, depth), and traced (doc, depth, rank)."""
    allowed = {"match": condition_sql(query), "all": "true", "none": "false"}[follow]
    seeds = ", ".join(f"({u})" for u in query.seeds())
    return f"""with recursive web as materialized ({web_sql}),
ent as materialized ({entity_sql}),
edge as materialized (select distinct src, dst from (select doc as src, s as dst from web where {allowed} union all select doc, o from web where {allowed}) where src <> dst and dst in (select uri from ent)),
walk(doc, depth) as (select uri, 0 from ent where uri in (select * from (values {seeds})) union select e.dst, w.depth + 1 from walk w join edge e on e.src = w.doc where w.depth < {bound}),
reached as materialized (select doc, min(depth) as depth from walk group by 1),
traced as materialized (select doc, depth, row_number() over (order by depth, doc) as rank from reached)"""
