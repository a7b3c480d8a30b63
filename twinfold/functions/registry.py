"""SQL names of the engine's functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession, functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StringType

from ..plans.shipping import ship


def register(spark: SparkSession) -> None:
    """``blake3``, ``dct_hash``, ``segment_hash``, ``normalise_tokens``, ``hamming64``, ``cosine_fx``, ``vector_mean`` and the table function ``hash_bands``."""
    ship(spark)

    @F.pandas_udf(StringType())
    def blake3(content: pd.Series) -> pd.Series:
        from .blake3 import hex_digests

        return pd.Series(hex_digests(content.tolist()), dtype=object)

    @F.pandas_udf(ArrayType(LongType()))
    def dct_hash(tokens: pd.Series) -> pd.Series:
        from . import arithmetic, text as txt

        return pd.Series(arithmetic.pack(arithmetic.dct_bits(txt.token_rasters(tokens.tolist(), txt.Digests(3)))).tolist(), dtype=object)

    @F.pandas_udf(ArrayType(LongType()))
    def segment_hash(pixels: pd.Series, width: pd.Series, height: pd.Series) -> pd.Series:
        import numpy as np

        from .segments import segment_hashes

        return pd.Series([segment_hashes(np.frombuffer(bytes(p), np.uint8).reshape(h, w)) for p, w, h in zip(pixels, width, height)])

    @F.pandas_udf(ArrayType(DoubleType()))
    def vector_mean(v: pd.Series) -> list:
        import numpy as np

        return np.round(np.mean(np.stack(v.to_list()), axis=0), 7).tolist()

    class Bands:
        def eval(self, h: str, n: int):
            width = len(h) // n
            for i in range(n):
                yield i, int(h[i * width : (i + 1) * width], 16)

    for name, f in {"blake3": blake3, "dct_hash": dct_hash, "segment_hash": segment_hash, "vector_mean": vector_mean}.items():
        spark.udf.register(name, f)
    spark.udtf.register("hash_bands", F.udtf(Bands, returnType="band bigint, value bigint"))
    spark.sql("create or replace temporary function hamming64(a bigint, b bigint) returns int return bit_count(a ^ b)")
    spark.sql("create or replace temporary function cosine_fx(a array<bigint>, b array<bigint>) returns bigint return cast(floor(aggregate(zip_with(a, b, (x, y) -> x * y), 0L, (s, x) -> s + x) / (sqrt(cast(aggregate(a, 0L, (s, x) -> s + x * x) as double)) * sqrt(cast(aggregate(b, 0L, (s, x) -> s + x * x) as double))) * 1048576 + 0.5) as bigint)")
    spark.sql(r"create or replace temporary function normalise_tokens(t string) returns string return trim(regexp_replace(lower(t), r'[^\p{L}\p{N}]+', ' '))")
