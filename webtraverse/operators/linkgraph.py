"""The link graph of retrieved documents: degrees, in-neighbourhoods, scores, PageRank, components and distances."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import discard, durable


def degrees(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(uri, indegree) and (doc, outdegree) of distinct links (src, dst)."""
    return edges.groupBy(F.col("dst").alias("uri")).agg(F.count("*").alias("indegree")), edges.groupBy(F.col("src").alias("doc")).agg(F.count("*").alias("outdegree"))


def rcc(found: DataFrame) -> DataFrame:
    """(doc, rcc): the number of solutions each document contributed to."""
    return found.select(F.explode("prov").alias("doc")).groupBy("doc").agg(F.count("*").alias("rcc"))


def two_step(edges: DataFrame, sources: DataFrame | None = None) -> DataFrame:
    """(src, dst): who reaches a URI in one or two steps, each once, never itself. With ``sources`` (doc) only those count:
    documents without a contribution add nothing to any score, so leaving them out is exact and avoids the square of a hub's degree."""
    first = edges if sources is None else edges.join(sources.select(F.col("doc").alias("src")), "src", "left_semi")
    second = first.select("src", F.col("dst").alias("mid")).join(edges.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "dst")
    return first.unionByName(second).where("src <> dst").distinct()


def solution_scores(edges: DataFrame, counts: DataFrame, steps: int = 1) -> DataFrame:
    """(uri, rcc_score, rel_score) of URIs with a contributor among their in-neighbours of up to ``steps`` steps."""
    some = counts.where("rcc > 0")
    pairs = two_step(edges, some) if steps == 2 else edges
    return pairs.join(some.select(F.col("doc").alias("src"), "rcc"), "src").groupBy(F.col("dst").alias("uri")).agg(F.sum("rcc").alias("rcc_score"), F.count("*").alias("rel_score"))


def pagerank(edges: DataFrame, damping: float = 0.85, rounds: int = 20, tolerance: float = 1e-6, start: DataFrame | None = None) -> DataFrame:
    """(uri, rank): with the mass of vertices without links spread over all; ``start`` (uri, rank) warms it up."""
    ends = durable(edges.select(F.col("src").alias("uri")).unionByName(edges.select(F.col("dst").alias("uri"))).distinct(), "vertices")
    n = ends.count()
    if not n:
        return ends.withColumn("rank", F.lit(0.0))
    out = edges.groupBy("src").agg(F.count("*").alias("degree"))
    weighed = durable(edges.join(out, "src"), "weighed")
    now = ends.withColumn("rank", F.lit(1.0 / n)) if start is None else ends.join(start, "uri", "left").select("uri", F.coalesce("rank", F.lit(1.0 / n)).alias("rank"))
    now = durable(now, "rank")
    for _ in range(rounds):
        moved = weighed.join(now.withColumnRenamed("uri", "src"), "src").groupBy(F.col("dst").alias("uri")).agg(F.sum(F.col("rank") / F.col("degree")).alias("in_rank"))
        total = now.agg(F.sum("rank")).first()[0]
        kept = moved.agg(F.sum("in_rank")).first()[0] or 0.0
        spread = (1 - damping) * total / n + damping * (total - kept) / n
        after = durable(now.join(moved, "uri", "left").select("uri", (F.lit(spread) + damping * F.coalesce("in_rank", F.lit(0.0))).alias("rank"), F.col("rank").alias("was")), "rank")
        change = after.agg(F.sum(F.abs(F.col("rank") - F.col("was")))).first()[0]
        discard(now)
        now = after
        if change < tolerance:
            break
    return now.select("uri", "rank")


def _spread(edges: DataFrame, colour: DataFrame) -> DataFrame:
    """The smallest colour that reaches each vertex along ``edges``."""
    now = durable(colour, "colour")
    while True:
        got = edges.join(now.withColumnRenamed("v", "src"), "src").groupBy(F.col("dst").alias("v")).agg(F.min("c").alias("seen"))
        after = durable(now.join(got, "v", "left").select("v", F.least("c", F.coalesce("seen", "c")).alias("c"), (F.coalesce("seen", "c") < F.col("c")).alias("moved")), "colour")
        moved = not after.where("moved").isEmpty()
        discard(now)
        now = after.select("v", "c")
        now._durable_path = after._durable_path
        if not moved:
            return now


def strong_components(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """(v, component): forward colouring, then each colour's root claims what reaches it backwards in its colour."""
    left = durable(vertices.select("v"), "left")
    edges = durable(edges.select("src", "dst"), "edges")
    done = []
    while not left.isEmpty():
        inside = durable(edges.join(left.withColumnRenamed("v", "src"), "src", "left_semi").join(left.withColumnRenamed("v", "dst"), "dst", "left_semi"), "inside")
        colour = _spread(inside, left.select("v", F.col("v").alias("c")))
        same = durable(inside.join(colour.toDF("src", "c"), "src").join(colour.toDF("dst", "c2"), "dst").where("c = c2").select("src", "dst", "c"), "same")
        claimed = [durable(colour.where("v = c").select("v", F.col("c").alias("component")), "claimed")]
        while True:
            new = same.join(claimed[-1].toDF("dst", "component"), "dst").where("c = component").select(F.col("src").alias("v"), "component").distinct()
            seen = claimed[0]
            for c in claimed[1:]:
                seen = seen.unionByName(c)
            new = durable(new.join(seen.select("v"), "v", "left_anti"), "claimed")
            if new.isEmpty():
                break
            claimed.append(new)
        seen = claimed[0]
        for c in claimed[1:]:
            seen = seen.unionByName(c)
        done.append(seen)
        left = durable(left.join(seen.select("v"), "v", "left_anti"), "left")
    out = vertices.select("v", F.lit(None).cast("long").alias("component")).limit(0) if not done else done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def diameter(vertices: DataFrame, edges: DataFrame, sample: int | None = None) -> int:
    """The longest finite distance, by a search from many sources at once; ``sample`` bounds the sources (by a hash of their ids) at scale."""
    sources = vertices if sample is None else vertices.orderBy(F.xxhash64("v"), "v").limit(sample)
    edges = durable(edges.select("src", "dst").join(vertices.toDF("src"), "src", "left_semi").join(vertices.toDF("dst"), "dst", "left_semi"), "edges")
    seen = last = durable(sources.select(F.col("v").alias("source"), F.col("v").alias("at")), "pairs")
    depth = 0
    while True:
        new = edges.join(last.select("source", F.col("at").alias("src")), "src").select("source", F.col("dst").alias("at")).distinct()
        last = durable(new.join(seen, ["source", "at"], "left_anti"), "pairs")
        if last.isEmpty():
            return depth
        depth += 1
        seen = durable(seen.unionByName(last), "seen")
