"""A quality classifier from positive and unlabelled text.

Trusted positives are documents labelled 1; everything else known is web text without a label. Negatives are never used: the risk on them is written as the unlabelled risk less the
positives' share, and because that difference may not be negative it is held at zero (the non-negative unbiased risk); when a batch drives it below, the step
goes the other way. The share of positives in web text, the class prior, is estimated first: with any score g, P_web(g >= t) / P_pos(g >= t) bounds the prior from above and comes near it where no
negatives are left. Features are statistics of the whole text: bigrams of character classes, word and line repetition, lengths.

Defined results: null and empty texts have the features of an empty text and are scored by them; repeated rows are scored alike; without positives every score is 0.5; an empty table gives an
empty result. ``lang``, ``source`` and ``doc_id`` are not inputs of a score. The training samples are bounded (``max_rows`` of either kind).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from .shared import fit_logistic, held_out, per_text

_CLASSES = 12


def _class_table() -> np.ndarray:
    t = np.full(256, 9, np.int64)
    for i in range(256):
        c = chr(i)
        if i >= 192:
            t[i] = 10
        elif i >= 128:
            t[i] = 11
        elif c.islower():
            t[i] = 0
        elif c.isupper():
            t[i] = 1
        elif c.isdigit():
            t[i] = 2
        elif c in " \t\r":
            t[i] = 3
        elif c == "\n":
            t[i] = 4
        elif c in "|<>{}[]=_\\/":
            t[i] = 5
        elif c in "!?":
            t[i] = 6
        elif c in ".,;:'\"()-":
            t[i] = 7
        elif c in "#$%&*@^~+":
            t[i] = 8
    return t


_CLASS = _class_table()
FEATURES = _CLASSES * _CLASSES + 9


def features(text: str | None) -> np.ndarray:
    raw = np.frombuffer((text if isinstance(text, str) else "").encode("utf-8", "surrogatepass"), np.uint8)
    c = _CLASS[raw]
    pairs = np.bincount(c[:-1] * _CLASSES + c[1:], minlength=_CLASSES * _CLASSES) if len(c) > 1 else np.zeros(_CLASSES * _CLASSES)
    words = text.split() if isinstance(text, str) else []
    lines = [x for x in (text or "").split("\n") if x.strip()] if isinstance(text, str) else []
    n, m = max(1, len(words)), max(1, len(lines))
    distinct = len(set(words))
    same = sum(a == b for a, b in zip(words, words[1:]))
    more = [
        np.log1p(len(words)), np.log1p(len(lines)), distinct / n, np.log1p(n) - np.log1p(distinct), same / n,
        len(raw) / n / 10, sum(w.isupper() for w in words) / n, 1 - len(set(lines)) / m, sum(len(w) == 1 for w in words) / n,
    ]
    return np.concatenate([np.sqrt(pairs / max(1, len(c) - 1)), more]).astype(np.float32)


class Network:
    """One hidden layer; trained on the non-negative risk with Adam."""

    def __init__(self, x: np.ndarray, hidden: int, seed: int):
        rng = np.random.default_rng(seed)
        self.mean, self.scale = x.mean(0), np.maximum(x.std(0), 1e-2)
        d = x.shape[1]
        self.p = [rng.normal(0, d**-0.5, (d, hidden)), np.zeros(hidden), rng.normal(0, hidden**-0.5, hidden), np.zeros(1)]

    def standard(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -8, 8)

    def raw(self, z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = np.tanh(z @ self.p[0] + self.p[1])
        return h, h @ self.p[2] + self.p[3]

    def gradient(self, z: np.ndarray, h: np.ndarray, by_output: np.ndarray) -> list[np.ndarray]:
        inner = by_output[:, None] * self.p[2] * (1 - h * h)
        return [z.T @ inner, inner.sum(0), h.T @ by_output, np.array([by_output.sum()])]

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(self.standard(x))[1], -30, 30)))


def class_prior(positive: np.ndarray, web: np.ndarray, seed: int = 3) -> float:
    """Upper bound on the share of positives among ``web``, tight where the score leaves no negatives; out-of-fold scores."""
    rng = np.random.default_rng(seed)
    x, y = np.vstack([positive, web]).astype(float), np.r_[np.ones(len(positive)), np.zeros(len(web))]
    z = np.clip((x - x.mean(0)) / np.maximum(x.std(0), 1e-2), -8, 8)
    fold, g = rng.integers(0, 2, len(x)), np.zeros(len(x))
    for f in (0, 1):
        w = fit_logistic(z[fold != f], y[fold != f], np.ones((fold != f).sum()), ridge=10.0, steps=15)
        g[fold == f] = z[fold == f] @ w[:-1]
    gp, gu = np.sort(g[y == 1]), np.sort(g[y == 0])
    cuts = np.quantile(gp, np.linspace(0.02, 0.8, 60))
    tail = lambda a, t: 1 - np.searchsorted(a, t, side="left") / len(a)
    return float(np.clip(min(tail(gu, t) / max(tail(gp, t), 1e-9) + (tail(gu, t) / len(gu)) ** 0.5 / max(tail(gp, t), 1e-9) for t in cuts), 0.02, 0.98))


def risk_gradient(net: Network, p: np.ndarray, u: np.ndarray, prior: float) -> tuple[float, float, list[np.ndarray]]:
    """The two parts of the risk on standardised positives ``p`` and unlabelled ``u`` (logistic loss): of positives, and of negatives as unlabelled less positives; and the step's gradient, of their sum, or, where
    the second part is negative, of its negation."""
    sigmoid = lambda a: 1 / (1 + np.exp(-np.clip(a, -30, 30)))
    (hp, fp), (hu, fu) = net.raw(p), net.raw(u)
    negative = np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()
    below = net.gradient(u, hu, sigmoid(fu) / len(u))
    above = net.gradient(p, hp, sigmoid(fp) * prior / len(p))
    part = [a - b for a, b in zip(below, above)]
    if negative >= 0:
        own = net.gradient(p, hp, -sigmoid(-fp) * prior / len(p))
        g = [a + b for a, b in zip(own, part)]
    else:
        g = [-a for a in part]
    return float(prior * np.logaddexp(0, -fp).mean()), float(negative), g


def train(positive: np.ndarray, web: np.ndarray, prior: float, hidden: int = 24, epochs: int = 40, batch: int = 512, rate: float = 3e-3, decay: float = 1e-4, seed: int = 7) -> Network:
    net = Network(np.vstack([positive, web]), hidden, seed)
    p, u = net.standard(positive.astype(float)), net.standard(web.astype(float))
    rng = np.random.default_rng(seed)
    m, v, t = [np.zeros_like(a) for a in net.p], [np.zeros_like(a) for a in net.p], 0
    for _ in range(epochs):
        parts = max(1, round(max(len(p), len(u)) / batch))
        for ip, iu in zip(np.array_split(rng.permutation(len(p)), parts), np.array_split(rng.permutation(len(u)), parts)):
            if not len(ip) or not len(iu):
                continue
            g = risk_gradient(net, p[ip], u[iu], prior)[2]
            t += 1
            for i, a in enumerate(g):
                a = a + decay * net.p[i]
                m[i] = 0.9 * m[i] + 0.1 * a
                v[i] = 0.999 * v[i] + 0.001 * a * a
                net.p[i] = net.p[i] - rate * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
    return net


def _features(docs: DataFrame, ids: DataFrame) -> np.ndarray:
    """Feature rows of a bounded set of documents."""

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"x": [features(t).tolist() for t in pdf["text"]], "doc_id": pdf["doc_id"]})

    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(ids), "doc_id")
    rows = own.mapInPandas(run, "x array<float>, doc_id long").orderBy("doc_id", "x").select("x").collect()
    return np.array([r["x"] for r in rows], np.float32).reshape(-1, FEATURES)


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", max_rows: int = 12_000) -> tuple[Network | None, float]:
    """Positives: labelled 1 outside the held-out fold. Web text: documents outside that fold without any label row."""
    named = labels.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).alias("_y"))
    first = lambda d: d.distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    positive = _features(docs, first(named.where("_y = 1").where(~held_out()).select("doc_id")))
    free = docs.select(F.col("doc_id").cast("long").alias("doc_id")).where(F.col("doc_id").isNotNull()).where(~held_out()).join(named.where("_y is not null"), "doc_id", "left_anti")
    web = _features(docs, first(free))
    if len(positive) < 2 or len(web) < 2:
        return None, 0.5
    prior = class_prior(positive, web)
    return train(positive, web, prior), prior


def score(docs: DataFrame, net: Network | None) -> DataFrame:
    def start():
        return lambda texts: {"score": net.score(np.stack([features(t) for t in texts])).tolist() if net and texts else [0.5] * len(texts)}

    return per_text(docs, start, "score double")


def predict(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, **parameters) -> DataFrame:
    """Fit and score: doc_id, held_out, score, predicted, prior."""
    net, prior = fit(docs, labels, **parameters)
    return score(docs, net).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), F.lit(prior).alias("prior"))
