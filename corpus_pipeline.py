"""From raw documents to packed training sequences.

Stages in order: toxic documents go, later copies of repeated line runs go, one document of each near-duplicate group stays, sources are mixed to their target weights, and the mix is packed
into sequences. Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from twinfold.llm import line_dedup, mixing, ngram_join, packing, toxicity
from twinfold.llm.queries import vocabulary
from twinfold.plans.bitmaps import drop_rows
from twinfold.plans.columns import Carried
from twinfold.plans.storage import materialise


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the nearest labelled examples call toxic go; all others stay as they are.

    Null and empty texts get the label's share among such examples and go only if that is a half or more; repeated rows go or stay together; without labels, and of an empty table, all stays.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return toxicity.without(docs, toxicity.fit(docs, labels))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs leave the texts; a document that keeps no line goes, one that never had any stays.

    Null and empty texts stay; of repeated rows the first keeps its lines; null doc_ids come last; a count of characters ``n_chars`` follows the text; an empty table stays empty.
    """
    carried = Carried(docs, "doc_id", "text")
    left = line_dedup.dedupe(carried.rows).where(~F.coalesce("emptied", F.lit(False)))
    return _counted(docs, left.select(*carried.back()))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays, all its columns as they were.

    Texts without a five-word shingle are compared as wholes; null and empty texts stay; rows are told apart even where doc_ids are null or repeated; an empty table stays empty.
    """
    carried = Carried(docs, "text")
    rows = materialise(carried.rows.withColumn("row", F.monotonically_increasing_id()), "documents")
    found = ngram_join.near_duplicates(rows.select(F.col("row").alias("doc_id"), "text"))
    gone = materialise(found.where("not kept").select(F.col("doc_id").alias("row")), "gone")
    return drop_rows(rows, gone, "row").select(*carried.back())


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: source weights 5, 2, 1, 150 % of all words, at most twice each.

    Texts without a word have size 0 and come once; a null source is a source of its own, last in order; repeated rows are documents of their own; an empty table stays empty.
    """
    carried = Carried(docs, "doc_id", "text", "source")
    return mixing.replicate(mixing.mix(carried.rows), carried.rows.columns).select(*carried.back())


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix as sequences of at most 1024 tokens; one row a piece. Null text is empty text; an empty table gives an empty result."""
    return packing.pack_documents(docs, *vocabulary())


def _counted(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """The same columns; where there is one count of characters, it follows the text."""
    if [c.lower() for c in docs.columns].count("n_chars") != 1 or [c.lower() for c in docs.columns].count("text") != 1:
        return rows
    name = next(c for c in docs.columns if c.lower() == "n_chars")
    return rows.withColumn(name, F.when(F.col("n_chars").isNotNull(), F.length("text")).cast(docs.schema[name].dataType))


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("ngram_jaccard", drop_near_duplicates),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Learned scores, sketches and packing are not SQL; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``, each stage's rows written and read again before the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
