"""Language identification: averaged hashed subword embeddings under a linear softmax, trained by stochastic gradient descent in numpy.

A text is its lower-cased letters with single spaces between words; its subwords are the byte n-grams (three and four bytes, spaces mark word ends), each hashed to a row of the
embedding. The mean over the whole text goes through one linear layer. Training takes windows of a bounded number of documents of each language outside the held-out fold; a part
of them is kept aside to fit the temperature of the softmax and the confidence below which a prediction is rejected (``rejected``), so that accepted ones reach ``precision``.

Defined results: texts that are null or have no letter are ``und`` with score 0; ties go to the language first in code-point order; repeated rows are predicted alike; without
labelled texts everything is ``und``; an empty table gives an empty result. ``lang``, ``source`` and ``doc_id`` are not inputs of a prediction.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from ..plans.shipping import ship
from .shared import held_out, per_text, pieces

_REST = re.compile(r"[\W\d_]+")
RESULT = "lang_pred string, score double, rejected boolean"


def subword_blocks(text: str | None, bits: int) -> Iterator[np.ndarray]:
    """Rows of the embedding, one for each n-gram of the whole text, in blocks of bounded size; nothing without a letter. Blocks share the bytes that an n-gram across them needs."""
    if not isinstance(text, str) or not any(map(str.isalpha, text)):
        return
    held = b""  # the last bytes of what is done
    for piece in (*pieces(text), None):
        if piece is None:
            new = b" "
        else:
            flat = _REST.sub(" ", piece.lower()).strip()
            if not flat:
                continue
            new = (" " + flat).encode("utf-8", "surrogatepass")
        b = np.frombuffer(held + new, np.uint8).astype(np.uint64)
        for n in (3, 4):
            lo = max(0, len(held) - n + 1)
            if len(b) - lo >= n:
                h = np.zeros(len(b) - lo - n + 1, np.uint64)
                for i in range(n):
                    h = h * np.uint64(0x100000001B3) + b[lo + i : len(b) - n + 1 + i] + np.uint64(n)
                yield ((h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - bits)).astype(np.int64)
        held = (held + new)[-3:]


def subwords(text: str | None, bits: int) -> np.ndarray:
    """All rows of a text at once."""
    return np.concatenate([np.zeros(0, np.int64), *subword_blocks(text, bits)])


def sampled(text: str | None, bits: int, window: int, windows: int, seed: int) -> list[np.ndarray]:
    """``windows`` sorted samples of ``window`` rows from the whole text, its rows counted first and never held together; a short text repeats itself."""
    total = sum(len(x) for x in subword_blocks(text, bits))
    if not total:
        return []
    rng = np.random.default_rng(seed)
    picks = [np.sort(rng.choice(total, window, replace=total < window)) for _ in range(windows)]
    out, at = [np.zeros(window, np.int64) for _ in picks], 0
    for block in subword_blocks(text, bits):
        for rows, pick in zip(out, picks):
            own = (pick >= at) & (pick < at + len(block))
            rows[own] = block[pick[own] - at]
        at += len(block)
    return [np.sort(x) for x in out]


class Model:
    def __init__(self, languages: list[str], bits: int, dim: int, seed: int):
        rng = np.random.default_rng(seed)
        self.languages, self.bits = languages, bits
        self.embedding = rng.uniform(-1 / dim, 1 / dim, (1 << bits, dim)).astype(np.float32)
        self.weight, self.bias = np.zeros((dim, len(languages)), np.float32), np.zeros(len(languages), np.float32)
        self.temperature, self.reject_at = 1.0, 0.0

    def logits(self, means: np.ndarray) -> np.ndarray:
        return means @ self.weight + self.bias

    def mean(self, blocks: Iterable[np.ndarray]) -> np.ndarray | None:
        """Of all rows of all blocks; None without a row."""
        total, n = np.zeros(self.embedding.shape[1]), 0
        for block in blocks:
            n += len(block)
            for i in range(0, len(block), 65_536):
                total += self.embedding[block[i : i + 65_536]].sum(axis=0, dtype=np.float64)
        return total / n if n else None

    def probabilities(self, logits: np.ndarray) -> np.ndarray:
        z = logits / self.temperature
        e = np.exp(z - z.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True)


def train(samples: list[tuple[np.ndarray, int]], languages: list[str], bits: int = 16, dim: int = 16, epochs: int = 6, batch: int = 64, rate: float = 0.5, seed: int = 29) -> Model:
    """Samples are windows of equal length, so that batches are rectangular."""
    model = Model(languages, bits, dim, seed)
    rng = np.random.default_rng(seed)
    x, y = np.stack([s for s, _ in samples]), np.array([c for _, c in samples])
    share = len(y) / (len(languages) * np.maximum(1, np.bincount(y, minlength=len(languages))))
    steps, done = epochs * -(-len(x) // batch), 0
    for _ in range(epochs):
        order = rng.permutation(len(x))
        for lo in range(0, len(x), batch):
            i = order[lo : lo + batch]
            h = model.embedding[x[i]].mean(axis=1)
            z = model.logits(h)
            p = np.exp(z - z.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            p[np.arange(len(i)), y[i]] -= 1
            p *= share[y[i], None] / len(i)
            lr = np.float32(rate * (1 - done / steps) * batch / 8)
            back = (p @ model.weight.T).astype(np.float32) / x.shape[1]
            model.weight -= lr * (h.T @ p).astype(np.float32)
            model.bias -= lr * p.sum(axis=0).astype(np.float32)
            flat, width = x[i].ravel(), x.shape[1]
            rows, inverse = np.unique(flat, return_inverse=True)
            for d in range(back.shape[1]):
                model.embedding[rows, d] -= lr * 40 * np.bincount(inverse, np.repeat(back[:, d], width), len(rows)).astype(np.float32)
            done += 1
    return model


def calibrate(model: Model, logits: np.ndarray, y: np.ndarray, precision: float) -> None:
    """Temperature by likelihood; then the smallest confidence from which predictions reach the precision."""

    def loss(t: float) -> float:
        z = logits / t
        return float(np.mean(np.log(np.exp(z - z.max(1, keepdims=True)).sum(1)) + z.max(1) - z[np.arange(len(y)), y]))

    model.temperature = min(np.geomspace(0.05, 20, 80), key=loss)
    p = model.probabilities(logits)
    best, right = p.max(axis=1), p.argmax(axis=1) == y
    order = np.argsort(-best)
    ok = np.flatnonzero(np.cumsum(right[order]) >= precision * np.arange(1, len(y) + 1))
    model.reject_at = float(best[order][ok[-1]]) if len(ok) else 1.0


def fit(docs: DataFrame, per_language: int = 1200, max_documents: int = 6000, max_languages: int = 500, least: int = 50, window: int = 400, windows: int = 3, bits: int = 16, dim: int = 16, precision: float = 0.98, seed: int = 29) -> Model | None:
    """Learns from about ``per_language`` documents of each language (by hash of doc_id) and their ``lang``, ``max_documents`` in all, but no less than about ``least`` of each: the driver's share does not grow with the corpus. Every value of ``lang`` is a class; more than ``max_languages`` of them are an error."""
    ship(docs.sparkSession)
    own = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).where(~held_out()).select(F.xxhash64("doc_id").alias("_h"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    counts = own.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(max_languages + 1).collect()
    if not counts:
        return None
    if len(counts) > max_languages:
        raise ValueError(f"more than {max_languages} values of lang: merge them or raise max_languages")
    languages = sorted(r["lang"] for r in counts)
    per_language = min(per_language, max(least, max_documents // len(languages)))
    limits = docs.sparkSession.createDataFrame([(r["lang"], min(1.0, per_language / r["n"])) for r in counts], "lang string, keep double")
    chosen = own.join(F.broadcast(limits), "lang").where(F.pmod(F.col("_h"), F.lit(1 << 30)) < F.col("keep") * (1 << 30))

    def samples_of(batches):
        """Windows of subwords, spread over the whole text."""
        for pdf in batches:
            found = [(h, lang, x) for h, lang, text in zip(pdf["_h"], pdf["lang"], pdf["text"]) for x in sampled(text, bits, window, windows, abs(int(h)))]
            yield pd.DataFrame([(h, lang, x.astype("<i4").tobytes()) for h, lang, x in found], columns=["h", "lang", "rows"])

    bound = 2 * per_language * windows * len(languages)
    got = chosen.mapInPandas(samples_of, "h long, lang string, rows binary").orderBy("h", "rows").limit(bound).collect()
    if not got:
        return None
    code = {lang: i for i, lang in enumerate(languages)}
    samples = [(np.frombuffer(r["rows"], "<i4"), code[r["lang"]], r["h"] % 10 == 0) for r in got]
    model = train([(x, y) for x, y, aside in samples if not aside] or [(x, y) for x, y, _ in samples], languages, bits, dim, seed=seed)
    aside = [(x, y) for x, y, a in samples if a] or [(x, y) for x, y, _ in samples]
    calibrate(model, model.logits(np.stack([model.mean([x]) for x, _ in aside])), np.array([y for _, y in aside]), precision)
    return model


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    def one(text: str | None) -> tuple[str, float, bool]:
        mean = model.mean(subword_blocks(text, model.bits)) if model else None
        if mean is None:
            return "und", 0.0, True
        p = model.probabilities(model.logits(mean[None]))[0]
        best = int(p.argmax())
        return model.languages[best], float(p[best]), bool(p[best] < model.reject_at)

    def run(texts: list) -> dict[str, list]:
        rows = [one(t) for t in texts]
        return {"lang_pred": [r[0] for r in rows], "score": [r[1] for r in rows], "rejected": [r[2] for r in rows]}

    return per_text(docs, lambda: run, RESULT)


def identify(docs: DataFrame, **parameters) -> DataFrame:
    """Fit and predict: doc_id, held_out, lang_pred, score, rejected."""
    return predict(docs, fit(docs, **parameters)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")
