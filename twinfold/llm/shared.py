"""What the learning operators share: the fold, the bounded labelled sample, and a logistic calibration."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..plans.shipping import ship


def held_out(doc_id: str = "doc_id") -> Column:
    """True where crc32(doc_id as text) mod 5 is 0; a null doc_id counts as the empty text and so is held out."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def labelled_ids(labels: DataFrame, label: str, bound: int) -> DataFrame:
    """``doc_id, label`` of at most ``bound`` labelled documents outside the held-out fold (per doc_id; smallest hashes first): small by construction."""
    return (
        labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull()).where(~held_out())
        .groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(label).cast("int").alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    )


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, bound: int) -> DataFrame:
    """``doc_id, text, label`` of at most ``bound`` labelled training documents; the label side is broadcast and the texts are not shuffled."""
    own = labelled_ids(labels, label, bound)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(own), "doc_id")


_SPACE = re.compile(r"\s")


def pieces(text: str | None, size: int = 1 << 20) -> Iterator[str]:
    """A text in pieces of about ``size`` characters, cut at white space, so that what is made of its words stays bounded; nothing for null. One word longer than that stays whole."""
    if not isinstance(text, str):
        return
    lo = 0
    while len(text) - lo > size:
        cut = _SPACE.search(text, lo + size)
        if cut is None:
            break
        yield text[lo : cut.start()]
        lo = cut.start()
    yield text[lo:] if lo else text


def per_text(docs: DataFrame, start: Callable[[], Callable[[list], dict[str, list]]], result: str, carry: dict[str, Column] | None = None) -> DataFrame:
    """Apply a function of texts in Arrow batches and keep ``doc_id`` (and ``carry``) beside its columns, bit by bit, nulls included.

    ``start`` runs once a task and returns the function; a list ``_row`` among its columns says which text each output row belongs to (else one row a text, in order).
    """
    ship(docs.sparkSession)
    own = {"doc_id": F.col("doc_id").cast("long")} | (carry or {})
    rows = docs.select(F.col("text").cast("string").alias("text"), *[c.alias(k) for k, c in own.items()])
    made = T._parse_datatype_string(result)
    schema = T.StructType([T.StructField(k, rows.schema[k].dataType) for k in own] + made.fields)
    arrow, names, results = to_arrow_schema(schema), list(own), [f.name for f in made.fields]

    def run(batches):
        work = start()
        for batch in batches:
            out = work(batch.column("text").to_pylist())
            at = out.pop("_row", None)
            kept = [batch.column(k) if at is None else batch.column(k).take(pa.array(at, pa.int64())) for k in names]
            kept = [a.cast(arrow.field(k).type) for k, a in zip(names, kept)]
            yield pa.RecordBatch.from_arrays(kept + [pa.array(out[k], arrow.field(k).type) for k in results], schema=arrow)

    return rows.mapInArrow(run, schema)


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1e-3, steps: int = 50) -> np.ndarray:
    """Weighted logistic regression with intercept (last coefficient) by damped Newton steps."""
    a = np.column_stack([x, np.ones(len(x))])
    w = np.zeros(a.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        g = a.T @ (weight * (y - p)) - ridge * w
        h = (a * (weight * p * (1 - p))[:, None]).T @ a + ridge * np.eye(len(w))
        step = np.clip(np.linalg.solve(h, g), -4, 4)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-6, 1 - 1e-6)
    return np.log(p / (1 - p))
