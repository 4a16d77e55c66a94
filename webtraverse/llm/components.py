"""Connected components by alternating stars, without collecting links or components.

Each round joins the links with the smallest neighbour of each vertex, which a map-side combine finds first, so the row of a hub is
never gathered in one task. Rounds are kept as tables in the shared folder.

Behaviour at the edges: links of a vertex to itself and links with a null end count for nothing; links may repeat and have any direction; no links
give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize


def _large_star(links: DataFrame) -> DataFrame:
    """Every larger neighbour of a vertex is linked to the smallest vertex in sight."""
    both = links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low"))
    return both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v")).where("u <> v").distinct()


def _small_star(links: DataFrame) -> DataFrame:
    """Links point from the larger end down; all lower neighbours of a vertex, and itself, are linked to the smallest of them."""
    down = links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = down.groupBy("u").agg(F.min("v").alias("low"))
    moved = down.join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v"))
    return moved.unionByName(low.select("u", F.col("low").alias("v"))).where("u <> v").distinct()


def _mark(links: DataFrame):
    return links.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()


def components(links: DataFrame) -> DataFrame:
    """(vertex, component): the smallest vertex that each linked vertex reaches; ``links`` are (u, v)."""
    now = materialize(links.where("u <> v").select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).distinct(), "links")
    mark = _mark(now)
    while mark["n"]:
        after = materialize(_small_star(_large_star(now)), "stars")
        new = _mark(after)
        discard(now)
        now = after
        if new == mark:
            break
        mark = new
    vertices = now.select(F.col("u").alias("vertex"), F.col("v").alias("component"))
    return vertices.unionByName(now.select(F.col("v").alias("vertex"), F.col("v").alias("component")).distinct())


def extend(known: DataFrame, links: DataFrame) -> DataFrame:
    """(vertex, component) after further ``links`` (u, v): only what they join is followed, between components instead of vertices."""
    name = known.select("vertex", "component")
    ends = links.select("u", "v").join(name.toDF("u", "cu"), "u", "left").join(name.toDF("v", "cv"), "v", "left")
    ends = materialize(ends.select("u", "v", F.coalesce("cu", "u").alias("cu"), F.coalesce("cv", "v").alias("cv")), "newlinks")
    moved = components(ends.select(F.col("cu").alias("u"), F.col("cv").alias("v"))).toDF("component", "now")
    fresh = ends.select(F.col("u").alias("vertex"), F.col("cu").alias("component")).unionByName(ends.select(F.col("v").alias("vertex"), F.col("cv").alias("component")))
    return name.unionByName(fresh).distinct().join(moved, "component", "left").select("vertex", F.coalesce("now", "component").alias("component"))
