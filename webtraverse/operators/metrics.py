"""Measures of an execution, of a grid of executions, and of the reachable part of a web."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .linkgraph import diameter, rcc, strong_components


BUCKET = 4_096


def solution_curve(found: DataFrame, by: tuple[str, ...] = (), bucket: int = BUCKET) -> DataFrame:
    """(t_avail, n, before, all_n): how many solutions come at each time, and how many came before it.

    Sums are taken within buckets of time and over the buckets before, so that no task orders more than a bucket's times, or all buckets.
    """
    counted = found.groupBy(*by, "t_avail").agg(F.count("*").alias("n")).withColumn("_b", F.floor(F.col("t_avail") / bucket))
    earlier = W.partitionBy(*(by or [F.lit(0)])).orderBy("_b").rowsBetween(W.unboundedPreceding, -1)
    sums = counted.groupBy(*by, "_b").agg(F.sum("n").alias("_n"), F.max("t_avail").alias("_last"))
    sums = sums.select(*by, "_b", F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_before"), F.sum("_n").over(W.partitionBy(*(by or [F.lit(0)]))).alias("all_n"), F.max("_last").over(earlier).alias("_last"))
    inside = W.partitionBy(*by, "_b").orderBy("t_avail")
    own = counted.join(sums, [*by, "_b"]).withColumn("before", F.col("_before") + F.coalesce(F.sum("n").over(inside.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    return own.withColumn("previous", F.coalesce(F.lag("t_avail").over(inside), "_last")).select(*by, "t_avail", "n", "before", "all_n", "previous")


def response_times(found: DataFrame, n_docs: int | DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Times of the first, the median and the last solution, and their shares of the whole; no row where there is no solution.

    ``found`` has ``t_avail``; the median is the solution number ceil(S / 2).
    """
    curve = solution_curve(found, by)
    half = F.min(F.when((F.col("before") + F.col("n")) * 2 >= F.col("all_n"), F.col("t_avail")))
    out = curve.groupBy(*by).agg(F.max("all_n").alias("n_solutions"), F.min("t_avail").alias("t_first"), half.alias("t_half"), F.max("t_avail").alias("t_last")).where("n_solutions > 0")
    out = out.join(n_docs, list(by)) if by else out.crossJoin(F.broadcast(n_docs)) if isinstance(n_docs, DataFrame) else out.withColumn("n_docs", F.lit(n_docs).cast("long"))
    return out.withColumns({"relRT1st": F.col("t_first") / F.col("n_docs"), "relRT50": F.col("t_half") / F.col("n_docs"), "relRTCmpl": F.col("t_last") / F.col("n_docs")})


def response_curve(found: DataFrame, fractions: list[float]) -> DataFrame:
    """(fraction, t): when each share of the solutions existed."""
    asked = F.explode(F.array(*map(F.lit, fractions))).alias("fraction")
    return solution_curve(found).select("*", asked).where(F.col("before") + F.col("n") >= F.ceil(F.col("fraction") * F.col("all_n"))).groupBy("fraction").agg(F.min("t_avail").alias("t"))


def kth_solution(found: DataFrame, wanted: tuple[int, ...]) -> DataFrame:
    """(k, t_avail): when the k-th solution existed, for each ``wanted`` k that there is."""
    asked = F.explode(F.array(*map(F.lit, wanted))).alias("k")
    return solution_curve(found).select("*", asked).where((F.col("before") < F.col("k")) & (F.col("k") <= F.col("before") + F.col("n"))).select("k", "t_avail")


def tiles(found: DataFrame, n_tiles: int = 4) -> DataFrame:
    """(tile, t_from, t_to, n): solutions in order of time, cut into parts of sizes that differ by one at most, larger ones first."""
    tile, small, more = F.col("tile"), F.expr(f"all_n div {n_tiles}"), F.col("all_n") % n_tiles
    last = tile * small + F.least(tile, more)
    first = (tile - 1) * small + F.least(tile - 1, more) + 1
    cut = solution_curve(found).select("*", F.explode(F.sequence(F.lit(1), F.lit(n_tiles))).alias("tile"))
    part = F.least(F.col("before") + F.col("n"), last) - F.greatest(F.col("before") + 1, first) + 1
    return cut.withColumn("part", part).where("part > 0").groupBy("tile").agg(F.min("t_avail").alias("t_from"), F.max("t_avail").alias("t_to"), F.sum("part").alias("n"))


def aggregate_runs(metrics: DataFrame, by: tuple[str, ...], measures=("relRT1st", "relRT50", "relRTCmpl")) -> DataFrame:
    """Geometric mean and standard deviation over the runs of a cell."""
    return metrics.groupBy(*by).agg(F.count("*").alias("runs"), *[F.exp(F.avg(F.log(m))).alias(m) for m in measures], *[F.coalesce(F.stddev_samp(m), F.lit(0.0)).alias(f"{m}_sd") for m in measures])


def compare_to_baseline(metrics: DataFrame, baseline: str = "fifo", threshold: float = 0.1, cell=("web_id", "query"), measures=("relRT1st", "relRT50", "relRTCmpl"), by: tuple[str, ...] = ()) -> DataFrame:
    """(approach, measure, n_cells, n_worse, n_better, pct_worse, pct_better): cells at least ``threshold`` worse or better than the baseline."""
    long = metrics.select(*cell, *by, "approach", F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.col(m).alias("value")) for m in measures])).alias("x")).select(*cell, *by, "approach", "x.*")
    base = long.where(F.col("approach") == baseline).select(*cell, "measure", F.col("value").alias("base"))
    ratio = F.round(F.col("value") / F.col("base"), 9)
    joined = long.where(F.col("approach") != baseline).join(base, [*cell, "measure"]).withColumn("worse", ratio >= 1 + threshold).withColumn("better", ratio <= 1 - threshold)
    out = joined.groupBy(*by, "approach", "measure").agg(F.count("*").alias("n_cells"), F.count_if("worse").alias("n_worse"), F.count_if("better").alias("n_better"))
    return out.withColumn("pct_worse", F.round(F.col("n_worse") * 100 / F.col("n_cells"), 1)).withColumn("pct_better", F.round(F.col("n_better") * 100 / F.col("n_cells"), 1))


def retrieval_model(n_docs: int, threads: int, latency_s: float) -> float:
    """Seconds that retrieval takes when ``threads`` lookups run at a time."""
    return -(-n_docs // threads) * latency_s


def relevance(reached: DataFrame, found: DataFrame) -> DataFrame:
    """Reached documents with their contribution count, 0 where there is none."""
    return reached.join(rcc(found), "doc", "left").withColumn("rcc", F.coalesce("rcc", F.lit(0)))


def subweb_stats(reached: DataFrame, edges: DataFrame, found: DataFrame, deep: bool = True, sample: int | None = None) -> DataFrame:
    """One row of statistics of a reachable subweb; seeds (distance 0) are left out of the distances."""
    docs = reached.select(F.col("doc").alias("v"))
    inner = edges.join(docs.toDF("src"), "src", "left_semi").join(docs.toDF("dst"), "dst", "left_semi")
    rated = relevance(reached, found)
    rel = F.col("rcc") > 0
    far = F.col("depth") > 0
    out = rated.agg(F.count("*").alias("docs"), F.count_if(rel).alias("relevant_docs"), *_distances(rel & far, "relevant"), *_distances(~rel & far, "irrelevant"))
    out = out.withColumn("edges", F.lit(inner.count())).withColumn("result_size", F.lit(found.count())).withColumn("relevant_pct", F.round(F.col("relevant_docs") * 100 / F.col("docs"), 1))
    if deep:
        out = out.withColumn("sccs", F.lit(strong_components(docs, inner).select("component").distinct().count())).withColumn("diameter", F.lit(diameter(docs, inner, sample)))
    return out


def _distances(who, name: str):
    d = F.when(who, F.col("depth"))
    return [F.avg(d).alias(f"{name}_mean"), F.stddev_samp(d).alias(f"{name}_sd"), F.min(d).alias(f"{name}_min"), F.max(d).alias(f"{name}_max")]


def predictors(rated: DataFrame, edges: DataFrame) -> DataFrame:
    """What about a subweb foretells how well an order may do: irrelevant documents beyond the farthest relevant one; relevant ones
    nearer than the median irrelevant one; relevant ones without a relevant in-neighbour of one or two steps."""
    rel = rated.where("rcc > 0")
    bounds = rated.agg(F.max(F.when(F.col("rcc") > 0, F.col("depth"))).alias("farthest"), F.expr("percentile_disc(0.5) within group (order by depth) filter (where rcc = 0)").alias("middle"))
    counts = rated.crossJoin(F.broadcast(bounds)).agg(F.count_if((F.col("rcc") == 0) & (F.col("depth") > F.col("farthest"))).alias("irrelevant_beyond"), F.count_if((F.col("rcc") > 0) & (F.col("depth") < F.col("middle"))).alias("relevant_before"))
    inner = edges.join(rel.select(F.col("doc").alias("dst")), "dst", "left_semi").join(rated.select(F.col("doc").alias("src")), "src", "left_semi")
    by_one = inner.join(rel.select(F.col("doc").alias("src")), "src", "left_semi").select(F.col("dst").alias("doc")).distinct()
    into = edges.join(rel.select(F.col("doc").alias("src")), "src", "left_semi").select("src", F.col("dst").alias("mid"))
    by_two = inner.select(F.col("src").alias("mid"), "dst").join(into, "mid").where("src <> dst").select(F.col("dst").alias("doc")).unionByName(by_one).distinct()
    lone1 = rel.join(by_one, "doc", "left_anti").agg(F.count("*").alias("lone_1step"))
    lone2 = rel.join(by_two, "doc", "left_anti").agg(F.count("*").alias("lone_2step"))
    return counts.crossJoin(lone1).crossJoin(lone2)


def correlation(rated: DataFrame, scores: DataFrame, name: str) -> DataFrame:
    """How a score of documents goes with their relevance."""
    joined = rated.join(scores.withColumnRenamed("uri", "doc"), "doc", "left").withColumn(name, F.coalesce(name, F.lit(0)).cast("double"))
    return joined.agg(F.round(F.corr(name, (F.col("rcc") > 0).cast("double")), 6).alias(f"corr_{name}"))
