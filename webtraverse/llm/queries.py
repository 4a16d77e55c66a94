"""Thin queries over the corpus operators: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, embedding_dedup, hash_forest, language_model, licenses, minhash_dedup, packing, quality, substring_dedup, url_filter


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_chosen_path_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(table(spark, sf_dir, "documents"), k=2, threshold=0.8)


def op2_hierarchical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def op3_link_graph_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"))


def op4_hash_prefix_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hash_forest.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0, k=10)


def op5_pairwise_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return quality.score_documents(docs, quality.train(docs, labels.where(~quality.held_out(F.col("doc_id")))))


def op6_inverted_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_duplicates(table(spark, sf_dir, "embeddings"), threshold=0.98)


def op7_monoid_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.round_trip_digest(table(spark, sf_dir, "documents"))


def op8_repeated_phrase_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(table(spark, sf_dir, "documents"))


def op9_cross_entropy_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents labelled good and not toxic are the target; all documents are the background."""
    targets = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")
    return language_model.cross_entropy_difference(table(spark, sf_dir, "documents"), targets)


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_documents(table(spark, sf_dir, "documents"))


OPERATORS = (
    op1_chosen_path_near_dedup,
    op2_hierarchical_packing,
    op3_link_graph_url_filter,
    op4_hash_prefix_forest,
    op5_pairwise_quality,
    op6_inverted_multi_index,
    op7_monoid_byte_bpe,
    op8_repeated_phrase_automata,
    op9_cross_entropy_difference,
    op10_license_scan,
)
QUERIES = {f.__name__: f for f in OPERATORS}

ORACLES: dict[str, str] = {
    "op3_link_graph_url_filter": url_filter.oracle(),
    "op6_inverted_multi_index": embedding_dedup.oracle(),
    "op10_license_scan": licenses.oracle(),
}
