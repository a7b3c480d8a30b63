"""What the two vector operators share: which rows take part, their bytes, rotations and pivots."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T


def usable(table: DataFrame, id_column: str = "vec_id", vector: str = "embedding") -> tuple[DataFrame, int]:
    """``(vec_id, v array<double>)`` of the rows that take part, and the dimension.

    Out: null ids; vectors that are null, empty or zero or hold null or non-finite components; vectors of another than the commonest
    dimension (ties: the smaller). Of repeated ids the least vector stays.
    """
    rows, dim = sound(table, id_column, vector)
    return least_of_each_id(rows), dim


def least_of_each_id(rows: DataFrame) -> DataFrame:
    return rows.groupBy("vec_id").agg(F.min("v").alias("v"))


def sound(table: DataFrame, id_column: str = "vec_id", vector: str = "embedding") -> tuple[DataFrame, int]:
    """:func:`usable` before repeated ids are settled, which deals all vectors out."""
    v = F.col(vector).cast("array<double>")
    sound = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = table.select(F.col(id_column).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & v.isNotNull() & F.coalesce(sound, F.lit(False)))
    dims = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    dim = dims["d"] if dims else 0
    return rows.where(F.size("v") == dim), dim


def matrix(values) -> np.ndarray:
    return np.array([np.asarray(x, np.float64) for x in values], np.float64)


def as_matrix(blobs, dim: int) -> np.ndarray:
    return np.frombuffer(b"".join(blobs), "<f8").reshape(-1, dim)


def rotation(dim: int, seed: int = 11) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def pivots(x: np.ndarray, k: int, seed: int = 5, rounds: int = 12) -> np.ndarray:
    """Lloyd's iterations from a random start; empty cells move to the points farthest from their pivots."""
    k = max(1, min(k, len(x)))
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        d = distances(x, c)
        own = d.argmin(axis=1)
        n = np.bincount(own, minlength=k)
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        full = n > 0
        c[full] = sums[full] / n[full, None]
        if (~full).any():
            c[~full] = x[np.argsort(-d[np.arange(len(x)), own], kind="stable")[: int((~full).sum())]]
    return c


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances."""
    return np.maximum((x * x).sum(1)[:, None] + (c * c).sum(1) - 2 * x @ c.T, 0)


DOUBLE_BLOB = T.BinaryType()
