"""A semi-join reducer of bounded size.

``reduce_by`` drops most rows of a wide table that cannot find a partner, before the join shuffles it. The partners' hashed keys
become a bitmap of at most 2**27 bits (16 MB), built by Spark's bitmap aggregate and broadcast. A set bit may be a coincidence, so the join still has to follow;
beyond the bitmap's capacity more rows pass, none is lost.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

MAX_BITS = 1 << 27
_PER_BUCKET = 32768  # bits of one bitmap of Spark's bitmap functions


def _spot(key: str, bits: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(bits)) + 1


def _hits(wide: DataFrame, keys: DataFrame, key: str, count: int | None) -> tuple[DataFrame, str]:
    """``wide`` with a further column, whose name no column of it has, that says whether the row may have a partner."""
    n = keys.count() if count is None else count
    bits = _PER_BUCKET
    while bits < min(MAX_BITS, 16 * n):
        bits *= 2
    free = "hit"
    while any(c.lower().startswith(free) for c in wide.columns):
        free = "_" + free
    bucket, at, map_, hit = (f"{free}_{x}" for x in ("bucket", "at", "map", "it"))
    spot = _spot(key, bits)
    maps = keys.select(F.bitmap_bucket_number(spot).alias(bucket), F.bitmap_bit_position(spot).alias(at)).groupBy(bucket).agg(F.bitmap_construct_agg(at).alias(map_))
    marked = wide.withColumns({bucket: F.bitmap_bucket_number(spot), at: F.bitmap_bit_position(spot)})
    byte = F.conv(F.hex(F.expr(f"substring({map_}, cast({at} div 8 as int) + 1, 1)")), 16, 10).cast("int")
    bit = F.coalesce(F.getbit(byte, (F.col(at) % 8).cast("int")) == 1, F.lit(False))
    return marked.join(F.broadcast(maps), bucket, "left").withColumn(hit, bit), hit


def _plain(rows: DataFrame, wide: DataFrame) -> DataFrame:
    return rows.select(*[F.col(f"`{c.replace('`', '``')}`") for c in wide.columns])


def reduce_by(wide: DataFrame, keys: DataFrame, key: str, count: int | None = None) -> DataFrame:
    """Rows of ``wide`` whose ``key`` may be among those of ``keys``; ``count`` is the number of keys, where known."""
    hits, hit = _hits(wide, keys, key, count)
    return _plain(hits.where(hit), wide)


def split_by(wide: DataFrame, keys: DataFrame, key: str, count: int | None = None) -> tuple[DataFrame, DataFrame]:
    """The rows that may have a partner and those that certainly have none; every row is in one of the two."""
    hits, hit = _hits(wide, keys, key, count)
    return _plain(hits.where(hit), wide), _plain(hits.where(f"not {hit}"), wide)


def drop_rows(wide: DataFrame, gone: DataFrame, key: str) -> DataFrame:
    """``wide`` without the rows whose key is in ``gone``; only rows that may be hit are shuffled."""
    touched, clean = split_by(wide, gone, key)
    return _plain(touched.join(gone.select(key), key, "left_anti"), wide).unionByName(clean)
