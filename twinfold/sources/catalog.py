"""Labelled collections on the given tables, and what one pass over their content yields.

A *corpus* row is ``dataset, image_id, path, subject, content``; a *signed* row has, in place of the content, ``length, digest, hi, lo`` (the 64-bit hash as two halves), ``seg`` (the crop-tolerant hash: one
checksum of its list of region hashes), the same of the aligned variant (``ahi, alo, aseg``, null where alignment failed), the feature vector ``vec`` (array of long, null where extraction failed) and the
quality ``q`` (null where missing). Everything after the signing pass reads signed rows; only the byte check reads the content of candidates again.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions import arithmetic, text as txt
from ..plans.shipping import ship

SCHEMA = "dataset string, image_id long, path string, subject string, length long, digest string, hi long, lo long, ahi long, alo long, seg string, aseg string, vec array<long>, q double"
ALL = ("digest", "dct", "segment", "vec", "q")
DETECT = ("digest", "dct", "segment")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def padded(c: str) -> Column:
    return F.lpad(F.col(c).cast("string"), 10, "0")


def _subject(kind: str) -> Column:
    return {"source": F.col("source"), "lang": F.col("lang"), "mix": F.concat("lang", F.lit("-"), (F.col("doc_id") % 3).cast("string"))}[kind]


def documents(spark: SparkSession, sf_dir: str, subject: str = "source") -> DataFrame:
    """``documents`` labelled by ``source`` (copies cross subjects), ``lang`` (they do not) or ``mix`` (both)."""
    d = table(spark, sf_dir, "documents")
    return d.select(F.lit(f"documents-{subject}").alias("dataset"), F.col("doc_id").alias("image_id"), F.concat("source", F.lit("/"), padded("doc_id")).alias("path"), _subject(subject).alias("subject"), F.col("text").alias("content"))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``pages`` by host: the control that has nearly no copies."""
    p = table(spark, sf_dir, "pages")
    return p.select(F.lit("pages").alias("dataset"), F.col("page_id").alias("image_id"), F.col("url").alias("path"), F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("subject"), F.col("html").alias("content"))


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = table(spark, sf_dir, "benchmark")
    return b.select(F.lit("benchmark").alias("dataset"), F.col("item_id").alias("image_id"), F.concat(F.lit("bench/"), padded("item_id")).alias("path"), F.lit("bench").alias("subject"), F.col("text").alias("content"))


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return c.select(F.lit("conversations").alias("dataset"), (F.col("conv_id") * 1000 + F.col("turn")).alias("image_id"), F.concat(padded("conv_id"), F.lit("/"), padded("turn")).alias("path"), F.col("conv_id").cast("string").alias("subject"), F.col("text").alias("content"))


def text_quality(content: Column) -> Column:
    """First quality provider: distinct share of the tokens in thousandths plus the length up to 1000; null below five tokens."""
    words = F.split(txt.flat(content), " ")
    n, d = F.size(words), F.size(F.array_distinct(words))
    return F.when(n >= 5, (F.floor(d * 1000 / n) + F.least(F.length(content), F.lit(1000))).cast("double"))


def spread(rows: DataFrame) -> DataFrame:
    """The rows of a small file over all cores: dealt anew only where the scan has fewer partitions than there are cores (never for large inputs)."""
    if rows.isStreaming:
        return rows
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores) if rows.rdd.getNumPartitions() < cores else rows


def sign(corpus: DataFrame, want=ALL) -> DataFrame:
    """One pass over the content: digest and tokens in the JVM, hashes and features in Arrow batches of token lines, computed over whole batches.

    ``want`` names what is computed (``digest``, ``dct``, ``segment``, ``vec``, ``q``); the columns of the rest are null. The content itself goes no further than the JVM.
    """
    ship(corpus.sparkSession)
    want = frozenset(want)
    if unknown := want - frozenset(ALL):
        raise ValueError(f"unknown signatures {sorted(unknown)}")
    content = F.col("content")
    own = ["dataset", "image_id", "path", "subject"]
    read = spread(corpus.where("content is not null").select(*own, "content")).select(
        *own, F.octet_length("content").cast("long").alias("length"), (F.sha2(content.cast("binary"), 256) if "digest" in want else F.lit(None).cast("string")).alias("digest"),
        F.length("content").alias("chars"), txt.lines_of(content).alias("lines"),
    )
    arrow = to_arrow_schema(T._parse_datatype_string(SCHEMA))

    def work(batches):
        three, four = txt.Digests(3, flag=True), txt.Digests(4)
        for batch in batches:
            made = dict.fromkeys(("hi", "lo", "ahi", "alo", "seg", "aseg", "vec", "q"))
            texts = batch.column("lines").to_pylist()
            n = len(texts)
            words = [t.split() for t in texts]
            sizes = np.fromiter(map(len, words), np.int64, n)
            if want & {"dct", "segment"}:
                coded = three.of([w for x in words for w in x])
                doc = np.repeat(np.arange(n), sizes)
                digits, keep = coded & 4095, coded >> 12 > 0
                there = np.bincount(doc, weights=keep, minlength=n) >= 5
                crop = keep & there[doc]
                gone = ~there
            if "dct" in want:
                half = arithmetic.pack(arithmetic.dct_bits(txt.rasters(doc, digits, n)))
                crops = arithmetic.pack(arithmetic.dct_bits(txt.rasters(doc[crop], digits[crop], n)))
                made |= {"hi": pa.array(half[:, 0]), "lo": pa.array(half[:, 1]), "ahi": pa.array(crops[:, 0], mask=gone), "alo": pa.array(crops[:, 1], mask=gone)}
            if "segment" in want:
                lines = [len(line.split()) for t in texts for line in t.split("\n")]
                line = np.repeat(np.arange(len(lines)), lines)
                made["seg"] = pa.array(txt.region_signatures(doc, line, digits, n))
                made["aseg"] = pa.array(np.array(txt.region_signatures(doc[crop], line[crop], digits[crop], n), object), pa.string(), mask=gone)
            if "vec" in want:
                made["vec"] = pa.array([txt.shingle_features(x, four) for x in words], pa.list_(pa.int64()))
            if "q" in want:
                made["q"] = pa.array([len(set(x)) * 1000 // len(x) + min(c, 1000) if len(x) >= 5 else None for x, c in zip(words, batch.column("chars").to_pylist())], pa.float64())
            yield pa.RecordBatch.from_arrays([pa.nulls(n, f.type) if made.get(f.name, 0) is None else made[f.name].cast(f.type) if f.name in made else batch.column(f.name).cast(f.type) for f in arrow], schema=arrow)

    return read.mapInArrow(work, SCHEMA)


def _hashed(corpus: DataFrame, schema: str, f) -> DataFrame:
    """``image_id`` and what ``f`` makes of the token strings of a batch."""
    ship(corpus.sparkSession)
    arrow = to_arrow_schema(T._parse_datatype_string(f"image_id long, {schema}"))

    def work(batches):
        digests = txt.Digests(3)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("image_id"), *f(batch.column("tokens").to_pylist(), digests)], schema=arrow)

    return spread(corpus.select("image_id", "content")).select("image_id", txt.flat(F.col("content")).alias("tokens")).mapInArrow(work, f"image_id long, {schema}")


def long_hash(corpus: DataFrame, low: int = 16) -> DataFrame:
    """The frequency hash with ``low`` x ``low`` coefficients, as words of 32 bits."""
    return _hashed(corpus, "words array<long>", lambda texts, d: [pa.array(arithmetic.pack(arithmetic.dct_bits(txt.token_rasters(texts, d), low)).tolist(), pa.list_(pa.int64()))])


def gradient_hash(corpus: DataFrame) -> DataFrame:
    """The gradient hash of whole texts: 8 x 9 cells, each compared with its left neighbour, as two halves."""

    def work(texts, digests):
        words = [(t or "").split() for t in texts]
        half = txt.gradients(np.repeat(np.arange(len(words)), [len(x) for x in words]), digests.of([w for x in words for w in x]), len(words))
        return [pa.array(half[:, 0]), pa.array(half[:, 1])]

    return _hashed(corpus, "hi long, lo long", work)
