"""The queries of this subpackage: thin, each gets its rows through its operator with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..plans.shipping import ship
from . import ann, embed_dedup, langid, line_dedup, mixing, ngram_join, packing, quality, sharding, toxicity


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vocabulary() -> tuple[str, str]:
    """The public vocabulary files, named once: JSON for the library that defines the ids, ranks for the fast one."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of at most 1024 tokens; one row a piece."""
    return packing.pack_documents(_table(spark, sf_dir, "documents"), *vocabulary())


def op2_entropy_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents mixed to 150 % of all words at source weights 5, 2, 1."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    sized = docs.select("doc_id", "source", mixing.word_count(F.col("text")).alias("_w"))
    return mixing.mix(sized, size=F.col("_w")).select("doc_id", "size", "source_size", "target", "taken", "copies", "rate")


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents joined with themselves on five-word shingles at Jaccard 0.8; one row a document."""
    found = ngram_join.near_duplicates(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "class_id", "n_links", "copies", "kept")


def op4_toxicity_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents scored by their nearest labelled examples."""
    return toxicity.predict(_table(spark, sf_dir, "documents").select("doc_id", "text"), _table(spark, sf_dir, "labels"))


def op5_adaptive_dimension_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 nearest of every vector whose id is divisible by 20, among all vectors."""
    return ann.search(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op6_quality_positive_unlabelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents scored for quality by the positive-unlabelled classifier."""
    return quality.predict(_table(spark, sf_dir, "documents").select("doc_id", "text"), _table(spark, sf_dir, "labels"))


def op7_rendezvous_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in shards 0 to 7 of equal weight, and where a ninth shard would put them."""
    out = sharding.assign(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")


def op8_line_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents without later copies of repeated line runs."""
    out = line_dedup.dedupe(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "lines", "removed_lines", "text", "emptied")


def op9_subspace_pigeonhole(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All vectors linked at cosine 0.9, with their components."""
    return embed_dedup.near_duplicates(_table(spark, sf_dir, "embeddings"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document."""
    return langid.identify(_table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_best_fit_packing": op1_best_fit_packing,
    "op2_entropy_mixing": op2_entropy_mixing,
    "op3_ngram_jaccard_join": op3_ngram_jaccard_join,
    "op4_toxicity_neighbours": op4_toxicity_neighbours,
    "op5_adaptive_dimension_scan": op5_adaptive_dimension_scan,
    "op6_quality_positive_unlabelled": op6_quality_positive_unlabelled,
    "op7_rendezvous_sharding": op7_rendezvous_sharding,
    "op8_line_runs": op8_line_runs,
    "op9_subspace_pigeonhole": op9_subspace_pigeonhole,
    "op10_language_id": op10_language_id,
}
ORACLES: dict[str, str] = {"op8_line_runs": line_dedup.ORACLE}
