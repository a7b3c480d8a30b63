"""Counts over sets and actions."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def classify(sets: DataFrame, corpus: DataFrame) -> DataFrame:
    """``set_id, images, subjects, kind``: ``intra`` within one subject, ``inter`` across several."""
    own = sets.join(corpus.select("image_id", "subject"), "image_id")
    return own.groupBy("set_id").agg(F.count("*").alias("images"), F.count_distinct("subject").alias("subjects")).withColumn("kind", F.when(F.col("subjects") > 1, "inter").otherwise("intra"))


def overview(corpus: DataFrame, sets: DataFrame) -> DataFrame:
    """One row a dataset: images, subjects, intra and inter duplicates with their subjects, their overlap, the combined count and share.

    Images and subjects are first reduced to one row each with two flags, so the distinct counts need no expansion.
    """
    kinds = sets.join(classify(sets, corpus).select("set_id", "kind"), "set_id")
    flags = kinds.groupBy("image_id").agg(F.max((F.col("kind") == "intra").cast("int")).alias("intra"), F.max((F.col("kind") == "inter").cast("int")).alias("inter"))
    per = corpus.select("dataset", "image_id", "subject").join(flags, "image_id", "left").groupBy("dataset", "subject").agg(
        F.count("*").alias("n"), F.coalesce(F.sum("intra"), F.lit(0)).alias("intra"), F.coalesce(F.sum("inter"), F.lit(0)).alias("inter"), F.count_if((F.col("intra") == 1) & (F.col("inter") == 1)).alias("both")
    )
    out = per.groupBy("dataset").agg(
        F.sum("n").alias("images"), F.count("*").alias("subjects"), F.sum("intra").alias("intra"), F.count_if(F.col("intra") > 0).alias("subjects_with_intra"),
        F.sum("inter").alias("inter"), F.count_if(F.col("inter") > 0).alias("subjects_with_inter"), F.sum("both").alias("both"),
    )
    combined = F.col("intra") + F.col("inter") - F.col("both")
    return out.withColumn("combined", combined).withColumn("share", F.round(combined.cast("double") / F.col("images"), 6))


def results(acts: DataFrame) -> DataFrame:
    """Removed and moved images."""
    return acts.agg(F.count_if(F.col("action") == "remove").alias("removed"), F.count_if(F.col("action") == "move").alias("moved"), F.count_if(F.col("action") == "keep").alias("kept"))


def detector_yield(sets: DataFrame) -> DataFrame:
    """Images found per detector and variant."""
    return sets.groupBy("detector", "variant").agg(F.count_distinct("image_id").alias("images"), F.count_distinct("set_id").alias("sets"))


def variant_yield(sets: DataFrame) -> DataFrame:
    """Images found by near detection on originals only, on aligned crops only, and on both."""
    per = sets.where("detector <> 'digest'").groupBy("image_id").agg(F.bool_or(F.col("variant") == "original").alias("o"), F.bool_or(F.col("variant") == "aligned").alias("a"))
    return per.agg(F.count_if(F.col("o") & ~F.col("a")).alias("original_only"), F.count_if(F.col("a") & ~F.col("o")).alias("aligned_only"), F.count_if(F.col("a") & F.col("o")).alias("both"))


def preprocess_failures(signed: DataFrame, sets: DataFrame) -> DataFrame:
    """Images whose alignment failed, and how many of them are duplicates by their originals."""
    known = sets.where("variant = 'original'").select("image_id").distinct().withColumn("dup", F.lit(1))
    rows = signed.select("dataset", "image_id", F.col("ahi").isNull().alias("failed")).join(known, "image_id", "left")
    return rows.groupBy("dataset").agg(F.count_if("failed").alias("failures"), F.count_if(F.col("failed") & F.col("dup").isNotNull()).alias("duplicates"))


def pair_quality(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision, recall and F1 of pairs (a < b)."""
    both = found.select("a", "b").distinct().withColumn("f", F.lit(1)).join(truth.select("a", "b").distinct().withColumn("t", F.lit(1)), ["a", "b"], "full_outer")
    sums = both.agg(F.count("f").alias("found"), F.count("t").alias("planted"), F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull()).alias("hits"))
    p, r = F.col("hits") / F.col("found"), F.col("hits") / F.col("planted")
    return sums.select("found", "planted", "hits", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(F.try_divide(2 * p * r, p + r), 6).alias("f1"))


def set_pairs(sets: DataFrame) -> DataFrame:
    """The pairs inside sets, for small collections with known copies."""
    a, b = sets.alias("a"), sets.alias("b")
    return a.join(b, (F.col("a.set_id") == F.col("b.set_id")) & (F.col("a.image_id") < F.col("b.image_id"))).select(F.col("a.image_id").alias("a"), F.col("b.image_id").alias("b")).distinct()


def costs(corpus: DataFrame, sets: DataFrame, components: DataFrame) -> DataFrame:
    """What the methods compute, by their counts: digests, candidate bytes' images, pairs of the correction, mated pairs all and circular."""
    k = components.groupBy("component").agg(F.count("*").alias("k")).agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0)).alias("correction_pairs"))
    n = corpus.groupBy("subject").agg(F.count("*").alias("n")).agg(F.sum("n").alias("digests"), F.sum(F.expr("n * (n - 1) div 2")).alias("all_mated"), F.sum(F.expr("case when n > 2 then n when n = 2 then 1 else 0 end")).alias("circular_mated"))
    c = sets.agg(F.count_distinct("image_id").alias("set_images"))
    return n.join(F.broadcast(k)).join(F.broadcast(c))  # one row each
