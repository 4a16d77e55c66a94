"""Webs of other shapes: hyperlinked pages, and chains of conversation turns; and triples from text files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.terms import BLANK, LITERAL, URI, hashed_id
from .basegraph import table

NEXT_TURN = 50
ID_BITS = (1 << 58) - 1


def page_parts(pages: DataFrame) -> DataFrame:
    """(page_id, scheme, host, path)."""
    rest = F.substring_index("url", "://", -1)
    return pages.select("page_id", F.substring_index("url", "://", 1).alias("scheme"), F.lower(F.regexp_extract(rest, "^([^/?#]*)", 1)).alias("host"), F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1).alias("path"))


def page_links(pages: DataFrame) -> DataFrame:
    """(page_id, href), distinct links of each page as they are written."""
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href")).distinct()


def page_web(pages: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(triples, resolve): documents are pages, links go to the host's own path; hrefs that lead to no page fail."""
    at = page_parts(pages)
    url_id = lambda host, path: F.xxhash64(host, path).bitwiseAND(F.lit(ID_BITS)) * 16 + 9
    own = at.select("page_id", "host", url_id(F.col("host"), F.col("path")).alias("doc"))
    target = url_id(F.when(F.col("href").contains("://"), F.regexp_extract("href", "://([^/?#]*)", 1)).otherwise(F.col("host")), F.regexp_replace("href", "^[a-z]+://[^/]*", ""))
    triples = page_links(pages).join(own, "page_id").select("doc", F.col("doc").alias("s"), F.lit(60).alias("p"), F.lit(URI).cast("byte").alias("o_kind"), target.alias("o"))
    good = own.select(F.col("doc").alias("uri"), "doc").distinct()
    bad = triples.select(F.col("o").alias("uri")).distinct().join(good, "uri", "left_anti").select("uri", F.lit(None).cast("long").alias("doc"))
    return triples, good.unionByName(bad)


def conversation_web(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(triples, resolve): a document for each turn, linked to the next one: long paths, on which depth and breadth differ most."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    node = lambda turn: (F.col("conv_id") * 4096 + turn) * 16 + 10
    here, there = node(F.col("turn")), node(F.col("turn") + 1)
    chain = turns.join(turns.select("conv_id", (F.col("turn") - 1).alias("turn")), ["conv_id", "turn"], "left_semi")
    triples = chain.select(here.alias("doc"), here.alias("s"), F.lit(NEXT_TURN).alias("p"), F.lit(URI).cast("byte").alias("o_kind"), there.alias("o"))
    return triples, turns.select(here.alias("uri"), here.alias("doc"))


NTRIPLE = r'^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"\S*)\s*\.\s*$'


def parse_ntriples(lines: DataFrame, doc: str = "file") -> DataFrame:
    """(doc, s, p, o_kind, o, o_str) from N-Triples lines (``value``); lines of any other form are left out. Blank nodes are scoped by document."""
    got = lines.where(F.col("value").rlike(NTRIPLE)).select(*[F.regexp_extract("value", NTRIPLE, i + 1).alias(x) for i, x in enumerate("spo")])
    name = F.lit(doc)
    iri = lambda c: F.xxhash64(c).bitwiseAND(F.lit(ID_BITS)) * 16 + 11
    node = lambda c: F.when(F.col(c).startswith("_:"), hashed_id(name, F.col(c))).when(F.col(c).startswith("<"), iri(F.col(c))).otherwise(hashed_id(F.col(c)))
    kind = F.when(F.col("o").startswith("_:"), BLANK).when(F.col("o").startswith("<"), URI).otherwise(LITERAL).cast("byte")
    return got.select(name.alias("doc"), node("s").alias("s"), iri(F.col("p")).alias("p"), kind.alias("o_kind"), node("o").alias("o"), F.when(F.col("o").startswith('"'), F.regexp_extract("o", r'^"((?:[^"\\]|\\.)*)"', 1)).alias("o_str"))
