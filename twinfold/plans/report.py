"""What a run should say about itself: skew of its keys, counts observed on the way, and its parameters."""

from __future__ import annotations

import json
import platform

import pyspark
from pyspark.sql import DataFrame, Observation, SparkSession, functions as F

from .storage import width


def skew(rows: DataFrame, *keys: str) -> DataFrame:
    """One row: rows, keys, largest group, and its share. A share above one over the number of partitions asks for salting."""
    per = rows.groupBy(*keys).agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("rows"), F.count("*").alias("keys"), F.max("n").alias("largest")).withColumn("share", F.round(F.col("largest").cast("double") / F.col("rows"), 6))


def salted_sum(rows: DataFrame, key: str, value: str, salts: int | None = None) -> DataFrame:
    """Sums by key in two steps, for aggregates without partial combination: (key, salt) first, then key. The salt comes from the row, so a rerun deals alike."""
    salts = salts or width(rows.sparkSession)
    first = rows.withColumn("_salt", F.pmod(F.xxhash64(*rows.columns), F.lit(salts))).groupBy(key, "_salt").agg(F.sum(value).alias("total"))
    return first.groupBy(key).agg(F.sum("total").alias("total"))


def observed(rows: DataFrame, name: str, **measures) -> tuple[DataFrame, Observation]:
    """Counts taken while the rows pass by, without another job: ``obs.get`` after the action."""
    obs = Observation(name)
    return rows.observe(obs, *[c.alias(k) for k, c in measures.items()] or [F.count(F.lit(1)).alias("rows")]), obs


def manifest(spark: SparkSession, **parameters) -> str:
    """Parameters, seeds and versions of a run as one JSON line."""
    keys = ("spark.sql.shuffle.partitions", "spark.sql.adaptive.enabled", "spark.sql.session.timeZone")
    return json.dumps({"spark": spark.version, "pyspark": pyspark.__version__, "python": platform.python_version(), "settings": {k: spark.conf.get(k) for k in keys}, "parameters": parameters}, sort_keys=True, default=str)
