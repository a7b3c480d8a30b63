"""Integer arithmetic behind the hashes and scores: every engine and every partitioning gets the same bits."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, functions as F

SIDE = 32
LOW = 8
#: Brightness of a cell by its count: min(255, floor(32 * log2(1 + count))), constant from 255 on.
LUMINANCE = [min(255, math.floor(32 * math.log2(1 + c))) for c in range(256)]
#: Fixed-point basis of the type-II transform: round(2**14 * cos(pi * (2x + 1) * u / 64)).
BASIS = [[round(16384 * math.cos(math.pi * (2 * x + 1) * u / (2 * SIDE))) for x in range(SIDE)] for u in range(16)]
#: Scores are cosines times 2**20, rounded half up.
SCALE = 1 << 20


def luminance(counts: np.ndarray) -> np.ndarray:
    return np.array(LUMINANCE, np.int64)[np.minimum(counts, 255)]


def dct_bits(rasters: np.ndarray, low: int = LOW) -> np.ndarray:
    """(n, 32, 32) integers to (n, low*low) booleans: low-frequency coefficient above the median of all of them."""
    t = np.array(BASIS[:low], np.int64)
    c = np.einsum("ux,nxy->nuy", t, rasters.astype(np.int64))
    c = np.einsum("nuy,vy->nuv", c, t).reshape(len(rasters), low * low)
    s = np.sort(c, axis=1)
    half = low * low // 2
    return 2 * c > (s[:, half - 1] + s[:, half])[:, None]


def gradient_bits(rasters: np.ndarray) -> np.ndarray:
    """(n, 8, 9) integers to (n, 64) booleans: brighter than the left neighbour."""
    return (rasters[:, :, 1:] > rasters[:, :, :-1]).reshape(len(rasters), -1)


def pack(bits: np.ndarray) -> np.ndarray:
    """Booleans, first most significant, to words of 32 bits as int64."""
    n, k = bits.shape
    return (bits.reshape(n, k // 32, 32).astype(np.int64) << np.arange(31, -1, -1)).sum(axis=2)


def box_resize(r: np.ndarray, rows: int, columns: int) -> np.ndarray:
    """Area mean with integer cell bounds, rounded down."""
    h, w = r.shape
    ys, xs = np.arange(rows + 1) * h // rows, np.arange(columns + 1) * w // columns
    total = np.zeros((h + 1, w + 1), np.int64)
    total[1:, 1:] = r.astype(np.int64).cumsum(0).cumsum(1)
    y0, y1 = ys[:-1], np.maximum(ys[1:], ys[:-1] + 1)
    x0, x1 = xs[:-1], np.maximum(xs[1:], xs[:-1] + 1)
    y1, x1 = np.minimum(y1, h), np.minimum(x1, w)
    s = total[y1][:, x1] - total[y0][:, x1] - total[y1][:, x0] + total[y0][:, x0]
    return s // ((y1 - y0)[:, None] * (x1 - x0))


def box_resize_many(stack: np.ndarray, rows: int, columns: int) -> np.ndarray:
    """:func:`box_resize` of (n, h, w) rasters of one shape."""
    n, h, w = stack.shape
    ys, xs = np.arange(rows + 1) * h // rows, np.arange(columns + 1) * w // columns
    total = np.zeros((n, h + 1, w + 1), np.int64)
    total[:, 1:, 1:] = stack.astype(np.int64).cumsum(1).cumsum(2)
    y0, x0 = ys[:-1], xs[:-1]
    y1, x1 = np.minimum(np.maximum(ys[1:], y0 + 1), h), np.minimum(np.maximum(xs[1:], x0 + 1), w)
    high, low = total[:, y1], total[:, y0]
    return (high[:, :, x1] - low[:, :, x1] - high[:, :, x0] + low[:, :, x0]) // ((y1 - y0)[:, None] * (x1 - x0))


def dot(a: Column, b: Column) -> Column:
    """Inner product of two arrays of long, exact."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    """Cosine of integer vectors: three exact sums, then one correctly rounded division. Null without features or for a zero vector."""
    norm = F.sqrt(dot(a, a).cast("double")) * F.sqrt(dot(b, b).cast("double"))
    return F.when(norm > 0, dot(a, b).cast("double") / norm)


def score(a: Column, b: Column) -> Column:
    """Fixed-point cosine: floor(cos * 2**20 + 1/2)."""
    return F.floor(cosine(a, b) * F.lit(float(SCALE)) + F.lit(0.5)).cast("long")


def hamming(hi: Column, lo: Column, hi2: Column, lo2: Column) -> Column:
    return (F.bit_count(hi.bitwiseXOR(hi2)) + F.bit_count(lo.bitwiseXOR(lo2))).cast("int")
