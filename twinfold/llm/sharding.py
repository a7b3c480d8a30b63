"""Sharding by rendezvous hashing, in DataFrame functions only.

Every (record key, shard) pair has a hash u in (0, 1); a record goes to the shard of least -ln(u) / weight. The law is ``key``: key and shards alone decide, shares follow the weights, and
a shard that is added takes records only into itself, since the other pairs' hashes stay. The slot numbers the records of a shard without gaps: counts by
(shard, salt) give each salt's first slot, a window inside (shard, salt) the rest, so no task sees a whole shard.

Defined results: a null key is the key ``null``; null text has no bytes (size 1, checksum 0); repeated rows share a shard and get slots of their own, in any order, which are interchangeable; an
empty table gives an empty result. Columns named as results (in any case) are replaced, others are carried along whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..plans.columns import Carried

SALT_DIGITS = 3  # hexadecimal: 4096 salts a shard


RESULT = ("size", "text_crc32", "law", "shard", "slot", "grown_shard")


def _key(key: str) -> Column:
    return F.coalesce(F.col(key).cast("string"), F.lit("null"))


def race(key: Column, shard: int, weight: float = 1.0) -> Column:
    """-ln(u) / weight of a pair; the least wins."""
    h = F.conv(F.substring(F.md5(F.concat(key, F.lit(f":{shard}"))), 1, 15), 16, 10).cast("long")
    return -F.log((h.cast("double") + 0.5) / F.lit(float(1 << 60))) / F.lit(float(weight))


def winner(key: Column, weights: list[float]) -> Column:
    runs = [F.struct(race(key, i, w).alias("t"), F.lit(i).alias("i")) for i, w in enumerate(weights) if w > 0]
    return F.array_min(F.array(*runs))["i"]


def assign(docs: DataFrame, weights: list[float] | None = None, grown: float | None = 1.0, key: str = "doc_id") -> DataFrame:
    """``docs`` with size, text_crc32, law, shard, slot and grown_shard (the shard once one of weight ``grown`` is added)."""
    weights = weights or [1.0] * 8
    carried = Carried(docs, key, "text", taken=RESULT)
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    name = _key(key)
    more = winner(name, [*weights, grown]) if grown else F.lit(None).cast("int")
    made = {"size": (F.octet_length(text) + 1).cast("long"), "text_crc32": F.crc32(text), "law": F.lit("key"), "shard": winner(name, weights), "grown_shard": more, "mark": F.md5(text)}
    out = carried.rows.select(F.struct(*carried.rows.columns).alias("row"), *[c.alias(k) for k, c in made.items()], F.col(key).alias("place"), F.substring(F.md5(F.concat(name, F.lit(":"), F.md5(text))), 1, SALT_DIGITS).alias("salt"))
    cells = out.groupBy("shard", "salt").agg(F.count("*").alias("n"))
    first = cells.select("shard", "salt", (F.sum("n").over(Window.partitionBy("shard").orderBy("salt")) - F.col("n")).alias("first"))
    inside = F.row_number().over(Window.partitionBy("shard", "salt").orderBy("place", "mark")) - 1
    # at most shards x 4096 cells, whatever the number of records
    done = out.withColumn("inside", inside).join(F.broadcast(first), ["shard", "salt"]).select("row.*", "size", "text_crc32", "law", "shard", (F.col("first") + F.col("inside")).alias("slot"), "grown_shard")
    return done.select(*carried.back(), *RESULT)
