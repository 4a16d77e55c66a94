"""Webs of linked documents: one document for each entity, link triples placed by two probabilities.

A literal triple stays in the document of its subject. A link triple goes with probability ``phi1`` into the documents of both ends;
otherwise with probability ``phi2`` into that of its subject alone, else into that of its object alone. The draws depend
on the triple and the seed only, so webs of one seed differ no more than their parameters make them.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.terms import LITERAL, MODULUS, URI, place_draws
from . import basegraph

SEED = 42


@dataclass(frozen=True)
class WebParameters:
    web_id: str
    phi1: float
    phi2: float
    seed: int = SEED

    @property
    def dense(self) -> bool:
        """The corpus-like web counts as dense, as do all from two thirds on."""
        return self.phi1 > 0.5


def _grid() -> tuple[WebParameters, ...]:
    webs = [WebParameters(f"w{round(a * 100)}_{round(b * 100)}", a, b) for a in (0.0, 0.33, 0.66) for b in (0.0, 0.33, 0.66, 1.0)]
    return (*webs, WebParameters("w100", 1.0, 1.0), WebParameters("w62_47", 0.62, 0.47))


WEBS = _grid()
CORPUS_LIKE = WEBS[-1]
COLUMNS = ("web_id", "doc", "s", "p", "o_kind", "o", "o_str", "o_dbl", "o_ts")


def _documents(phi1, phi2, seed: int):
    u1, u2 = place_draws(F.col("s"), F.col("p"), F.col("o"), seed)
    both, subject, object_ = F.array("s", "o"), F.array("s"), F.array("o")
    return F.when(F.col("o_kind") != URI, subject).when(u1 < phi1, both).when(u2 < phi2, subject).otherwise(object_)


def place(triples: DataFrame, web: WebParameters = CORPUS_LIKE) -> DataFrame:
    """The triples of one web, a row for each document that holds them."""
    return triples.withColumn("web_id", F.lit(web.web_id)).withColumn("doc", F.explode(F.array_distinct(_documents(F.lit(web.phi1), F.lit(web.phi2), web.seed)))).select(*COLUMNS)


def all_webs(triples: DataFrame, webs=WEBS) -> DataFrame:
    """All webs of one seed from one scan: the table of parameters is a literal array of their number."""
    seeds = {w.seed for w in webs}
    if len(seeds) > 1:
        raise ValueError("webs of one call share a seed")
    params = F.array(*[F.struct(F.lit(w.web_id).alias("web_id"), F.lit(w.phi1).alias("phi1"), F.lit(w.phi2).alias("phi2")) for w in webs])
    placed = triples.withColumn("w", F.explode(params))
    docs = _documents(F.col("w.phi1"), F.col("w.phi2"), seeds.pop())
    return placed.withColumn("doc", F.explode(F.array_distinct(docs))).withColumn("web_id", F.col("w.web_id")).select(*COLUMNS)


def build(spark: SparkSession, sf_dir: str, web: WebParameters = CORPUS_LIKE, literals: bool = False) -> DataFrame:
    return place(basegraph.triples(spark, sf_dir, literals), web)


def resolve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(uri, doc, status): entities lead to their document, predicate URIs fail."""
    good = basegraph.entities(spark, sf_dir).select("uri", F.col("uri").alias("doc"), F.lit("ok").alias("status"))
    bad = basegraph.link_triples(spark, sf_dir).select((F.col("p").cast("long") * 16).alias("uri")).distinct().select("uri", F.lit(None).cast("long").alias("doc"), F.lit("failed").alias("status"))
    return good.unionByName(bad)


def estimate_phi(web: DataFrame) -> DataFrame:
    """(web_id, phi1, phi2, n_links): the share of link triples in both documents, and of those in one the share in the subject's."""
    links = web.where(F.col("o_kind") == URI).groupBy("web_id", "s", "p", "o").agg(F.max((F.col("doc") == F.col("s")).cast("int")).alias("at_s"), F.max((F.col("doc") == F.col("o")).cast("int")).alias("at_o"))
    both = F.col("at_s") + F.col("at_o") == 2
    counted = links.groupBy("web_id").agg(F.count("*").alias("n_links"), F.count_if(both).alias("n_both"), F.count_if(~both & (F.col("at_s") == 1)).alias("n_subject"))
    single = F.col("n_links") - F.col("n_both")
    return counted.select("web_id", (F.col("n_both") / F.col("n_links")).alias("phi1"), F.when(single > 0, F.col("n_subject") / single).alias("phi2"), "n_links")


def write_webs(web: DataFrame, path: str, files_per_web: int = 16) -> None:
    """Partitioned by web, clustered by document, with bloom filters, so that a lookup reads few row groups."""
    (web.repartition(files_per_web, "web_id", F.pmod(F.xxhash64("doc"), F.lit(files_per_web))).sortWithinPartitions("doc", "p")
     .write.mode("overwrite").partitionBy("web_id").option("parquet.bloom.filter.enabled#doc", "true").parquet(path))


def web_sql(web: WebParameters = CORPUS_LIKE) -> str:
    """Link triples of a web as SQL for DuckDB: (doc, s, p, o)."""
    m = MODULUS
    return f"""
select distinct unnest(case when u1 < {web.phi1} then [s, o] when u2 < {web.phi2} then [s] else [o] end) as doc, s, p, o from (
  select s, p, o, (h * 48271 % {m}) / {m} as u1, (h * 69621 % {m}) / {m} as u2 from (
    select s, p, o, ((s % {m}) * 1000003 + p::bigint * 7919 + (o % {m}) * 31337 + {web.seed} * 101) % {m} as h from ({basegraph.LINK_SQL})))"""
