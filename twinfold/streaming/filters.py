"""Duplicate filters for a growing collection.

Batches and streams give the same rows: the stream decides earlier, the batch job stays the authority (a late file of smaller path makes the stateful operator take back what it kept).
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions import arithmetic
from ..operators.detect import bands
from ..plans.storage import shared_dir


def arriving(spark: SparkSession, path: str, schema, files_per_trigger: int | None = None) -> DataFrame:
    """Parquet files as a stream. A table that is one file is named by a pattern, since a stream wants a folder or a glob."""
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path if not path.endswith(".parquet") else path[:-1] + "*")


def drain(stream: DataFrame, mode: str = "append", name: str = "stream", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there now and read its exactly-once file sink back. ``complete`` and ``update`` keep the last state of each batch.

    With a ``checkpoint`` the run resumes where the last one ended, and the rows of all its runs lie beside it."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/twinfold/{name}-{uuid.uuid4().hex}"
    out, mark = (f"{checkpoint}-rows", checkpoint) if checkpoint else (f"{base}/rows", f"{base}/checkpoint")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", mark).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", out).start()
    else:

        def put(batch: DataFrame, k: int) -> None:
            batch.write.mode("overwrite" if mode == "complete" else "append").parquet(out)

        query = writer.foreachBatch(put).start()
    query.awaitTermination()
    schema = stream.schema
    return spark.read.schema(schema).parquet(out) if _exists(spark, out) else spark.createDataFrame([], schema)


def _exists(spark: SparkSession, path: str) -> bool:
    sc = spark.sparkContext
    p = sc._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(sc._jsc.hadoopConfiguration()).exists(p)


def stamped(docs: DataFrame) -> DataFrame:
    """Documents with an arrival time a second apart, from the second day on (time 0 would already be late)."""
    return docs.withColumn("arrived", F.timestamp_seconds(F.lit(86400) + F.col("doc_id")))


def exact_filter(stream: DataFrame, delay: str = "30 days") -> DataFrame:
    """First arrival of each digest within the watermark; state is bounded by the delay."""
    return stream.withColumn("digest", F.sha2(F.col("text").cast("binary"), 256)).withWatermark("arrived", delay).dropDuplicatesWithinWatermark(["digest"])


def against_store(stream: DataFrame, store: DataFrame) -> DataFrame:
    """Arrivals whose digest the persisted store does not hold. The store is read anew in each batch."""
    return stream.withColumn("digest", F.sha2(F.col("text").cast("binary"), 256)).join(store.select("digest"), "digest", "left_anti")


def fill_store(stream: DataFrame, store_path: str, checkpoint: str) -> None:
    """Unbounded filter: each batch keeps its first arrivals that the store lacks and appends their digests; a batch that is run again finds its own marks and adds nothing."""
    spark = stream.sparkSession

    def merge(batch: DataFrame, k: int) -> None:
        new = batch.groupBy("digest").agg(F.min("doc_id").alias("doc_id"))
        if _exists(spark, store_path):
            old = spark.read.schema("digest string, doc_id long, batch long").parquet(store_path).where(F.col("batch") != k)
            new = new.join(old.select("digest"), "digest", "left_anti")
        new.withColumn("batch", F.lit(k).cast("long")).write.mode("overwrite").parquet(f"{store_path}/batch={k}")

    stream.withColumn("digest", F.sha2(F.col("text").cast("binary"), 256)).writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(merge).start().awaitTermination()


def near_filter(signed_stream: DataFrame, store: DataFrame, radius: int = 6) -> DataFrame:
    """Arrivals within ``radius`` bits of a stored hash: ``image_id, known`` by bands, checked exactly. ``store(rep, hi, lo)`` has one row a hash."""
    known = store.select("rep", F.col("hi").alias("h2"), F.col("lo").alias("l2"), F.explode(bands(F.col("hi"), F.col("lo"), radius + 1)).alias("k")).select("rep", "h2", "l2", "k.band", "k.value")
    new = signed_stream.select("image_id", "hi", "lo", F.explode(bands(F.col("hi"), F.col("lo"), radius + 1)).alias("k")).select("image_id", "hi", "lo", "k.band", "k.value")
    d = arithmetic.hamming(F.col("hi"), F.col("lo"), F.col("h2"), F.col("l2"))
    return new.join(known, ["band", "value"]).where(d <= radius).select("image_id", F.col("rep").alias("known"))


def _keep_first() -> StatefulProcessor:
    """Per digest the smallest path so far; emits ``keep`` for it and ``unkeep`` for what it replaces. The class is made here, so that it travels by value to stream workers."""

    class KeepFirst(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.best = handle.getValueState("best", "path string, images long")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
            paths = [p for pdf in rows for p in pdf["path"]]
            old = self.best.get() if self.best.exists() else None
            low = min(paths if old is None else [*paths, old[0]])
            out = []
            if old is None or low != old[0]:
                if old is not None:
                    out.append((key[0], old[0], "unkeep"))
                out.append((key[0], low, "keep"))
            self.best.update((low, len(paths) + (old[1] if old else 0)))
            yield pd.DataFrame(out, columns=["digest", "path", "action"])

        def close(self) -> None:
            pass

    return KeepFirst()


def keep_changes(stream: DataFrame) -> DataFrame:
    """``digest, path, action`` as arrivals change which copy is kept. Needs the RocksDB state store."""
    rows = stream.select(F.sha2(F.col("text").cast("binary"), 256).alias("digest"), "path")
    return rows.groupBy("digest").transformWithStateInPandas(_keep_first(), "digest string, path string, action string", "Append", "None")
