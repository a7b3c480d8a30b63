"""Choice of the primary detection, landmark alignment and warping."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F

#: The public five-point template of 112 x 112 face crops.
FIVE_POINT = [(38.2946, 51.6963), (73.5318, 51.5014), (56.0252, 71.7366), (41.5493, 92.3655), (70.7299, 92.2041)]
SIZE = 112


def primary(detections: DataFrame, width: Column, height: Column, w_size: float = 1.0, w_center: float = 2.0, w_score: float = 1.0) -> DataFrame:
    """One detection an image of ``boxes array<struct<x1,y1,x2,y2,score,landmarks>>``: relative area, closeness to the centre and confidence, weighted (our choice); ties to the first. Null without any."""

    def value(b: Column) -> Column:
        area = (b["x2"] - b["x1"]) * (b["y2"] - b["y1"]) / (width * height)
        dx, dy = (b["x1"] + b["x2"]) / 2 - width / 2, (b["y1"] + b["y2"]) / 2 - height / 2
        near = 1 - F.sqrt(dx * dx + dy * dy) / (F.sqrt(width * width + height * height) / 2)
        return area * w_size + near * w_center + b["score"] * w_score

    scored = F.transform("boxes", lambda b, i: F.struct(value(b).alias("value"), (-i).alias("first"), b.alias("box")))
    best = F.aggregate(scored, F.lit(None).cast("struct<value:double,first:int>"), lambda s, x: F.when(s.isNull() | (x["value"] > s["value"]), F.struct(x["value"].cast("double").alias("value"), x["first"].alias("first"))).otherwise(s))
    return detections.withColumn("_best", best).withColumn("primary_index", -F.col("_best.first")).withColumn("primary", F.get("boxes", -F.col("_best.first"))).drop("_best")


def similarity_transform(landmarks: Column, template: list[tuple[float, float]] = FIVE_POINT) -> Column:
    """struct(a, b, tx, ty) of the least-squares rotation, scale and shift landmarks -> template: x' = a x - b y + tx, y' = b x + a y + ty.

    In complex numbers the centred problem has one unknown, the sum of conj(z) w over the sum of |z|^2.
    """
    n = float(len(template))
    mu, mv = sum(p[0] for p in template) / n, sum(p[1] for p in template) / n
    total = lambda f: F.aggregate(landmarks, F.lit(0.0), lambda s, p: s + f(p))
    mx, my = total(lambda p: p["x"]) / n, total(lambda p: p["y"]) / n
    goal = F.array(*[F.struct(F.lit(u - mu).alias("u"), F.lit(v - mv).alias("v")) for u, v in template])
    pairs = F.zip_with(landmarks, goal, lambda p, q: F.struct((p["x"] - mx).alias("x"), (p["y"] - my).alias("y"), q["u"].alias("u"), q["v"].alias("v")))
    fold = lambda f: F.aggregate(pairs, F.lit(0.0), lambda s, p: s + f(p))
    size = fold(lambda p: p["x"] * p["x"] + p["y"] * p["y"])
    a = fold(lambda p: p["x"] * p["u"] + p["y"] * p["v"]) / size
    b = fold(lambda p: p["x"] * p["v"] - p["y"] * p["u"]) / size
    return F.when(size > 0, F.struct(a.alias("a"), b.alias("b"), (F.lit(mu) - a * mx + b * my).alias("tx"), (F.lit(mv) - b * mx - a * my).alias("ty")))


def warp_array(raster: np.ndarray, a: float, b: float, tx: float, ty: float, size: int = SIZE) -> np.ndarray:
    """The crop: inverse map and bilinear sampling, edges repeated."""
    yy, xx = np.mgrid[0:size, 0:size].astype(np.float64)
    u, v, d = xx - tx, yy - ty, a * a + b * b
    x, y = (a * u + b * v) / d, (-b * u + a * v) / d
    h, w = raster.shape
    x, y = np.clip(x, 0, w - 1), np.clip(y, 0, h - 1)
    x0, y0 = np.minimum(x.astype(int), w - 2 if w > 1 else 0), np.minimum(y.astype(int), h - 2 if h > 1 else 0)
    x1, y1 = np.minimum(x0 + 1, w - 1), np.minimum(y0 + 1, h - 1)
    fx, fy = x - x0, y - y0
    top, low = raster[y0, x0] * (1 - fx) + raster[y0, x1] * fx, raster[y1, x0] * (1 - fx) + raster[y1, x1] * fx
    return np.floor(top * (1 - fy) + low * fy + 0.5).astype(np.int64)


def warp(images: DataFrame, size: int = SIZE) -> DataFrame:
    """``images(image_id, width, height, pixels binary, matrix)`` to ``image_id, aligned binary``; a missing matrix gives a missing crop."""

    def work(batches):
        for pdf in batches:
            out = []
            for w, h, p, m in zip(pdf["width"], pdf["height"], pdf["pixels"], pdf["matrix"]):
                out.append(None if m is None else warp_array(np.frombuffer(p, np.uint8).reshape(h, w), m["a"], m["b"], m["tx"], m["ty"], size).astype(np.uint8).tobytes())
            yield pd.DataFrame({"image_id": pdf["image_id"], "aligned": out})

    return images.select("image_id", "width", "height", "pixels", "matrix").mapInPandas(work, "image_id long, aligned binary")
