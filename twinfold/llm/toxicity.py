"""Toxicity by the nearest labelled examples under TF-IDF cosine, found exactly in a block-max inverted index.

Terms are the words of the lower-cased text. Every word of every labelled example is in the space; document frequencies are counted over all documents.
A term's idf is multiplied by ``telling``, a smooth power of its log odds ratio between the labels: never 0, and the same whichever label is the common one. Without it the many rare words of a text outweigh its few
telling ones. Terms fall into impact classes by weight, a factor of two each; postings are read class by class, heaviest first, and each example, and each block of examples at its largest, has the norm of
what its lighter classes hold. After some postings only blocks, then examples, can still be among the k nearest whose sum plus the product of the norms left reaches the k-th best sum; once few are left they are
finished alone. So the k nearest are exact. Their labels vote with weights growing as the distance falls; a logistic curve fitted on leave-one-out votes makes the vote a probability. The examples that voted
are the evidence.

Defined results: null, empty and term-less texts are at distance 1 from every example and get the (smoothed) share of the label among such examples; ties in cosine go to the smaller doc_id; repeated rows are scored
alike; without labelled rows every score is 0; an empty table gives an empty result. Whole texts are read, in pieces of bounded size; words of over 40 letters stand for themselves through their checksum.
``lang``, ``source`` and ``doc_id`` are not inputs of a score.
"""

from __future__ import annotations

import functools
import math
import re
import zlib
from collections import Counter
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..plans.bitmaps import drop_rows
from ..plans.columns import Carried
from ..plans.shipping import ship
from ..plans.storage import discard, materialise
from .shared import fit_logistic, held_out, labelled_ids, logit, pieces

_WORD = re.compile(r"\w+")
RESULT = "score double, evidence array<struct<doc_id:long,cosine:double,label:int>>, terms array<string>"
_CLASSES = np.arange(14)  # of impact, a factor of two each
NOTHING = np.zeros(0, np.int32), np.zeros(0, np.int64)


def term(word: str) -> str:
    """A word is its own term; over 40 letters it stands for itself through its checksum."""
    return word if len(word) <= 40 else f"{word[:32]}#{zlib.crc32(word.encode('utf-8', 'surrogatepass'))}"


class Terms:
    """The known terms, sorted, as one Arrow array; only who looks words up makes a dictionary of them."""

    def __init__(self, names: list[str]):
        self.names = pa.array(names, pa.string())

    def __getstate__(self) -> dict:
        return {"names": self.names}

    @functools.cached_property
    def number(self) -> dict[str, int]:
        return {t: i for i, t in enumerate(self.names.to_pylist())}

    def _of(self, words) -> np.ndarray:
        """Numbers of distinct words, -1 for unknown ones."""
        at = np.fromiter(map(self.number.get, words, repeat(-1)), np.int64, len(words))
        if max(map(len, words), default=0) > 40:
            for i, w in enumerate(words):
                if len(w) > 40:
                    at[i] = self.number.get(term(w), -1)
        return at

    def counts(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """The known terms of a whole text, sorted, and how often each occurs."""
        t, n = [NOTHING[1]], [NOTHING[1]]
        for piece in pieces(text):
            words = Counter(_WORD.findall(piece.lower()))
            t.append(self._of(words))
            n.append(np.fromiter(words.values(), np.int64, len(words)))
        t, n = np.concatenate(t), np.concatenate(n)
        t, n = t[t >= 0], n[t >= 0]
        order = np.argsort(t, kind="stable")
        t, n = t[order].astype(np.int32), n[order]
        if len(t) and (np.diff(t) == 0).any():  # words of several pieces
            first = np.flatnonzero(np.diff(t, prepend=-1))
            t, n = t[first], np.add.reduceat(n, first)
        return t, n


def _spans(lo: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The positions of all ranges of ``length`` from ``lo``, one after the other."""
    return np.repeat((lo - np.cumsum(length) + length).astype(np.int32), length) + np.arange(length.sum(), dtype=np.int32)


@functools.cache
def _rows(block: int, blocks: int) -> np.ndarray:
    return np.arange(block)[:, None] * blocks


class BlockMaxIndex:
    """Unit vectors (dicts, or their lengths, terms and weights as arrays); ``top`` gives the exact k nearest by cosine.

    ``weight`` of the terms orders the impact classes; without it the root mean square of a term's postings does.
    """

    classes = len(_CLASSES)

    def __init__(self, vectors: list | tuple, ids: np.ndarray, labels: np.ndarray, block: int = 32, weight: np.ndarray | None = None):
        if not isinstance(vectors, tuple):
            vectors = np.array([len(v) for v in vectors], np.int64), np.array([t for v in vectors for t in v], np.int32), np.array([x for v in vectors for x in v.values()], np.float32)
        length, t, x = vectors
        self.ids, self.labels, self.block, self.n = ids, labels, block, len(length)
        self.blocks = -(-self.n // block)
        self.slot = np.arange(self.n) % block * self.blocks + np.arange(self.n) // block  # examples of a block lie a row apart, so that maxima over blocks are maxima over rows
        self.of = np.full(self.blocks * block, -1, np.int32)
        self.of[self.slot] = np.arange(self.n)
        df = np.bincount(t, minlength=0 if weight is None else len(weight))
        self.size = len(df)
        if weight is None:
            weight = np.sqrt(np.bincount(t, weights=x.astype(float) ** 2, minlength=self.size) / np.maximum(df, 1))
        most = weight.max(initial=0) or 1.0
        self.group = np.clip(np.ceil(np.log2(most / np.maximum(weight, most * 1e-9))), 0, self.classes - 1).astype(np.int8)
        self.end = np.cumsum(length).astype(np.int32)  # fewer than 2**31 postings
        self.start = np.zeros((self.classes, self.n), np.int32)  # of what lies after each class
        self.left = np.zeros((self.classes, self.blocks * block), np.float32)
        self.ptr = np.concatenate([[0], np.cumsum(df)])
        self.posting = np.empty((len(t), 2), np.int32)  # slot and weight (its bits) side by side
        self.t, self.x = t, x  # ordered by class in place, example by example
        free = self.ptr[:-1].copy()
        for lo in range(0, self.n, 2048):  # by parts, for memory
            hi = min(lo + 2048, self.n)
            e = slice(self.end[lo] - length[lo], self.end[hi - 1])
            own, value, row = t[e].copy(), x[e].copy(), np.repeat(np.arange(hi - lo), length[lo:hi])
            order = np.argsort(own, kind="stable")
            sorted_ = own[order]
            n = np.bincount(sorted_, minlength=self.size)
            place = free[sorted_] + np.arange(len(order)) - (np.cumsum(n) - n)[sorted_]
            self.posting[place, 0], self.posting[place, 1] = self.slot[row[order] + lo], value[order].view(np.int32)
            free += n
            key = row * self.classes + self.group[own]
            order = np.argsort(key, kind="stable")
            self.t[e], self.x[e] = own[order], value[order]
            held = np.bincount(key, minlength=(hi - lo) * self.classes).reshape(-1, self.classes)
            square = np.bincount(key, weights=value.astype(float) ** 2, minlength=(hi - lo) * self.classes).reshape(-1, self.classes)
            self.start[:, lo:hi] = ((self.end - length)[lo:hi, None] + np.cumsum(held, axis=1)).T
            self.left[:, self.slot[lo:hi]] = (np.sqrt(np.maximum(square[:, ::-1].cumsum(axis=1)[:, ::-1] - square, 0)) * 1.000001 + 1e-7).T
        self.most = self.left.reshape(self.classes, block, self.blocks).max(axis=1) if self.n else self.left
        self.dense, self.read = np.zeros(self.size, np.float32), 0

    def top(self, query, k: int, without: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """Positions and cosines of the k nearest with a positive cosine, nearest first, ties to the smaller id."""
        t, q = (np.array(list(query), np.int64), np.array(list(query.values()), float)) if isinstance(query, dict) else query
        known = t < self.size
        t, q = t[known], q[known].astype(float)
        group = self.group[t]
        order = np.argsort(group, kind="stable")
        t, q, group = t[order], q[order], group[order]
        first = self.ptr[t]
        length = self.ptr[t + 1] - first
        later = np.cumsum((q * q)[::-1])[::-1]
        before = np.zeros(len(t) + 1, np.int64)
        np.cumsum(length, out=before[1:])
        ends = np.unique(np.searchsorted(group, _CLASSES, side="right"))  # of the classes among the query's terms
        cost = before[ends]
        score = np.zeros(self.blocks * self.block)
        done, j, at = 0, -1, None
        while done < len(t):
            j = max(j + 1, int(np.searchsorted(cost, before[done] + 6000)) - 1)  # classes of about 6000 postings together, one at least
            end = int(ends[j])
            n = length[done:end]
            i = _spans(first[done:end], n)
            pair = self.posting[i]
            added = np.repeat(q[done:end], n) * pair[:, 1].view(np.float32)
            if len(i) < 8000:
                np.add.at(score, pair[:, 0], added)
            else:
                score += np.bincount(pair[:, 0], weights=added, minlength=len(score))
            done = end
            if end == len(t) or self.n <= k + 1:
                continue
            # Only an example whose sum and norms left reach the k-th best sum can be among the k nearest; first whole blocks fall, then single examples.
            coming, g, rest = int(cost[j + 1] - cost[j]), group[end - 1], math.sqrt(later[end]) * 1.000001
            table = score.reshape(self.block, self.blocks)
            peak = table.max(axis=0)
            best = table[:, np.argpartition(peak, self.blocks - k - 1)[self.blocks - k - 1 :]].ravel() if self.blocks > k else score
            floor = np.partition(best, len(best) - k - 1)[len(best) - k - 1] - 1e-9  # one more than k: ``without`` may be among them
            alive = np.flatnonzero(peak + rest * self.most[g] >= floor)
            if 4 * len(alive) > self.blocks:
                some = np.flatnonzero(score + rest * self.left[g] >= floor)
            else:
                some = (_rows(self.block, self.blocks) + alive).ravel()
                some = some[score[some] + rest * self.left[g, some] >= floor]
            own = self.of[some]
            n = self.end[own] - self.start[g, own]
            if n.sum() < coming + 5000:  # finishing them costs less than reading the next class
                if own.min() < 0:
                    some, n, own = some[own >= 0], n[own >= 0], own[own >= 0]
                self.dense[t[end:]] = q[end:]
                i = _spans(self.start[g, own], n)
                at, found = own, score[some] + np.bincount(np.repeat(np.arange(len(own)), n), weights=self.dense[self.t[i]] * self.x[i], minlength=len(own))
                self.dense[t[end:]] = 0
                break
        self.read += int(before[done])
        if at is None:
            at, found = np.arange(self.n), score[self.slot]
        ok = (found > 0) & (at != without)
        at, found = at[ok], found[ok]
        if len(at) > k:
            ok = found >= np.partition(found, len(found) - k)[len(found) - k] - 1e-12
            at, found = at[ok], found[ok]
        order = np.lexsort((self.ids[at], -np.round(found, 12)))[:k]
        return at[order], found[order]


class Model:
    """Terms, their weights, and the counts of the labelled sample (packed, example by example, similar ones beside each other); each worker builds the index from them once."""

    def __init__(self, terms: Terms, weight: np.ndarray, ids: np.ndarray, labels: np.ndarray, length: np.ndarray, counts: list[bytes], empty: tuple[int, int], k: int):
        self.terms, self.weight, self.k = terms, weight, k
        self.ids, self.labels, self.length, self.counts = ids, labels, length, counts
        n0, p0 = empty
        total, positive = n0 + len(ids), p0 + int(labels.sum())
        self.prior = positive / total if total else 0.0
        self.alone = (p0 + self.prior) / (n0 + 1) if total else 0.0
        self.curve = np.array([1.0, 0.0])
        self.shared = self.corpus = self.fitted = None  # of the driver

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "index"} | {"shared": None, "corpus": None, "fitted": None}

    @functools.cached_property
    def index(self) -> BlockMaxIndex:
        """Made of the examples in their order here, decoded by parts."""
        total = self.length.sum()
        t, x, at = np.empty(total, np.int32), np.empty(total, np.float32), 0
        for lo in range(0, len(self.ids), 2048):
            length = self.length[lo : lo + 2048]
            pairs = [_unpacked(x) for x in self.counts[lo : lo + 2048]]
            own, n = (np.concatenate([p[c] for p in pairs]) for c in (0, 1))
            row = np.repeat(np.arange(len(length)), length)
            v = (1 + np.log(n)) * self.weight[own]
            v /= np.sqrt(np.bincount(row, weights=v * v))[row]
            t[at : at + len(own)], x[at : at + len(own)] = own, v
            at += len(own)
        if TaskContext.get() is not None:
            self.counts = None  # a worker has no further use for them
        return BlockMaxIndex((self.length, t, x), self.ids, self.labels, weight=self.weight)

    def calibrate(self, spark: SparkSession) -> None:
        """Fit the curve on leave-one-out votes of at most 4000 examples, taken by the workers."""
        self.shared = shared = spark.sparkContext.broadcast(self)
        if len(self.ids) < 20 or not 0 < self.labels.sum() < len(self.labels):
            return
        some = np.random.default_rng(1).permutation(len(self.ids))[:4000]

        def votes(batches):
            model = shared.value
            index = model.index
            for pdf in batches:
                at = some[pdf["id"].to_numpy()]
                own = [slice(index.end[i - 1] if i else 0, index.end[i]) for i in at]
                yield pd.DataFrame({"id": pdf["id"], "y": index.labels[at], "vote": [model.vote(*index.top((index.t[e], index.x[e]), model.k, without=int(i))) for i, e in zip(at, own)]})

        rows = sorted(spark.range(len(some), numPartitions=max(1, min(len(some) // 100, spark.sparkContext.defaultParallelism))).mapInPandas(votes, "id long, y int, vote double").collect())
        self.curve = fit_logistic(logit(np.array([r["vote"] for r in rows]))[:, None], np.array([r["y"] for r in rows], float), np.ones(len(rows)))
        self.curve[0] = max(self.curve[0], 0.0)

    def release(self) -> None:
        """Take the model from the executors; the next use sends it again."""
        if self.shared is not None:
            self.shared.unpersist()
            self.shared = None

    def vector(self, t: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Unit vector of sorted terms and their counts."""
        v = (1 + np.log(n)) * self.weight[t]
        norm = math.sqrt(v @ v)
        return t, (v / norm if norm else v).astype(np.float32)

    def vote(self, at: np.ndarray, cosine: np.ndarray) -> float:
        """The neighbours' labels by cosine over distance (a far example hardly counts), with half a vote for the base rate."""
        near = np.minimum(cosine, 1)
        w = near / (1.05 - near)
        return float((w @ self.index.labels[at] + self.prior / 2) / (w.sum() + 0.5))

    def score(self, t: np.ndarray, n: np.ndarray) -> tuple[float, list[dict]]:
        at, cosine = self.index.top(self.vector(t, n), self.k) if len(t) else NOTHING
        if not len(at):
            return self.alone, []
        p = 1 / (1 + math.exp(-float(np.clip(self.curve[0] * logit(np.array(self.vote(at, cosine))) + self.curve[1], -30, 30))))
        return p, [{"doc_id": int(self.index.ids[i]), "cosine": float(min(c, 1.0)), "label": int(self.index.labels[i])} for i, c in zip(at[:5], cosine[:5])]


def telling(n: np.ndarray, p: np.ndarray, rows: float, positive: float, pseudo: float = 4.0) -> np.ndarray:
    """How far terms in ``n`` of ``rows`` examples, ``p`` of them positive, go with either label: |log odds ratio| with ``pseudo`` examples at the base rate added, squared; 1 for all terms if one label is absent."""
    base = positive / rows
    if not 0 < base < 1:
        return np.ones(len(n))
    odds = np.log((p + pseudo * base) / (n - p + pseudo * (1 - base)) * ((1 - base) / base))
    return (np.abs(odds) + 0.01) ** 2


def _packed(t: np.ndarray, n: np.ndarray) -> bytes:
    """Differences of the terms, then the counts in one byte each, or four where one needs them. (The table they go into is compressed.)"""
    if not len(t):
        return b""
    small = n.max() < 256
    return np.diff(t, prepend=np.int32(0)).astype("<i4").tobytes() + n.astype("u1" if small else "<i4").tobytes() + (b"\1" if small else b"\4")


def _unpacked(counts: bytes) -> tuple[np.ndarray, np.ndarray]:
    if not counts:
        return NOTHING
    wide = counts[-1]
    m = (len(counts) - 1) // (4 + wide)
    return np.cumsum(np.frombuffer(counts, "<i4", m), dtype=np.int32), np.frombuffer(counts, "u1" if wide == 1 else "<i4", m, 4 * m).astype(np.int32)


def counted(docs: DataFrame, terms) -> DataFrame:
    """``doc_id, mark, counts``: every text's known terms and how often they occur, packed; ``mark`` is the same for equal texts. Written once, so that texts are split into words once."""
    ship(docs.sparkSession)
    text = F.col("text").cast("string")
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.md5(text.cast("binary")), F.lit("")).alias("mark"), text.alias("text"))

    def work(batches):
        for batch in batches:
            packed = [_packed(*terms.value.counts(x)) for x in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("mark"), pa.array(packed, pa.binary())], ["doc_id", "mark", "counts"])

    return materialise(read.mapInArrow(work, "doc_id long, mark string, counts binary"), "counted")


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", max_labelled: int = 40_000, k: int = 15) -> Model:
    """Learn from labelled rows outside the held-out fold; at most ``max_labelled`` of them (documented bound), all of them indexed. The model keeps the term counts of ``docs``."""
    spark = docs.sparkSession
    ship(spark)
    own = materialise(labelled_ids(labels, label, max_labelled), "labelled")
    sample = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(own), "doc_id")

    def tally(batches):
        held: dict[str, list[int]] = {}
        rows = [0, 0]
        for pdf in batches:
            for text, y in zip(pdf["text"], pdf["label"]):
                rows[y] += 1
                for t in {term(w) for piece in pieces(text) for w in set(_WORD.findall(piece.lower()))}:
                    x = held.setdefault(t, [0, 0])
                    x[0] += 1
                    x[1] += y
            if len(held) > 300_000:
                yield pd.DataFrame([(t, *x) for t, x in held.items()], columns=["term", "n", "p"])
                held = {}
        held[""] = [sum(rows), rows[1]]  # no word: all rows
        yield pd.DataFrame([(t, *x) for t, x in held.items()], columns=["term", "n", "p"])

    tallied = sample.mapInPandas(tally, "term string, n long, p long").groupBy("term").agg(F.sum("n").cast("int").alias("n"), F.sum("p").cast("int").alias("p"))
    by_term = tallied.toArrow().sort_by("term")
    rows, positive = (int(by_term[c][0].as_py()) if len(by_term) else 0 for c in ("n", "p"))
    if not rows:
        return Model(Terms([]), np.zeros(0), *[np.zeros(0, np.int64)] * 3, [], (0, 0), k)
    by_term = by_term.slice(1)
    terms = Terms(by_term["term"].to_pylist())
    weight = telling(by_term["n"].to_numpy(), by_term["p"].to_numpy(), rows, positive)
    del by_term
    known = spark.sparkContext.broadcast(terms)
    corpus = counted(docs, known)
    size = len(weight)

    def frequency(batches):
        count = np.zeros(size + 1, np.int64)
        for batch in batches:
            count[-1] += batch.num_rows
            for x in batch.column(0).to_pylist():
                count[_unpacked(x)[0]] += 1
        at = np.flatnonzero(count)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(count[at])], ["t", "n"])

    df = np.zeros(size + 1)
    found = corpus.select("counts").mapInArrow(frequency, "t int, n long").groupBy("t").agg(F.sum("n").alias("n")).toArrow()
    df[found["t"].to_numpy()] = found["n"].to_numpy()
    weight = weight * (np.log((df[-1] + 1) / (df[:-1] + 1)) + 1)
    weights = spark.sparkContext.broadcast(weight)

    def examples(batches):
        for batch in batches:
            strongest, length = [], []
            for x in batch.column("counts").to_pylist():
                t, n = _unpacked(x)
                strongest.append(int(t[np.argmax((1 + np.log(n)) * weights.value[t])]) if len(t) else -1)
                length.append(len(t))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in ("doc_id", "label", "counts")], pa.array(strongest, pa.int32()), pa.array(length, pa.int64())], ["doc_id", "label", "counts", "strongest", "length"])

    labelled = corpus.join(F.broadcast(own), "doc_id").select("doc_id", "label", "counts").mapInArrow(examples, "doc_id long, label int, counts binary, strongest int, length long").toArrow()
    labelled = labelled.sort_by([("strongest", "ascending"), ("doc_id", "ascending")])
    empty = labelled.filter(pc.equal(labelled["length"], 0))
    full = labelled.slice(len(empty))  # those without a term come first
    model = Model(terms, weight, *[full[c].to_numpy() for c in ("doc_id", "label", "length")], full["counts"].to_pylist(), (len(empty), int(pc.sum(empty["label"]).as_py() or 0)), k)
    del labelled, full
    known.destroy()
    weights.destroy()
    model.calibrate(spark)
    model.corpus, model.fitted = corpus, docs
    discard(own)
    return model


def _votes(rows: DataFrame, model: Model, work, schema: str) -> DataFrame:
    """Run ``work(model, remembered scores by mark, batch)`` over packed counts."""
    model.shared = shared = model.shared or rows.sparkSession.sparkContext.broadcast(model)
    curve = model.curve

    def run(batches):
        model = shared.value
        model.curve = curve
        known: dict = {}
        for batch in batches:
            if len(known) > 50_000:
                known.clear()
            yield work(model, known, batch)

    return rows.mapInArrow(run, schema)


def _score(model: Model, known: dict, mark: str, counts: bytes) -> tuple[float, list[dict], list[str]]:
    hit = known.get(mark)
    if hit is None:
        t, n = _unpacked(counts)
        strong = np.sort(t[np.argsort(-model.weight[t], kind="stable")[:20]])
        hit = known[mark] = (*model.score(t, n), model.terms.names.take(pa.array(strong, pa.int32())).to_pylist())
    return hit


def _of(docs: DataFrame, model: Model) -> DataFrame:
    """The packed counts of ``docs``: those made while fitting, if the model was fitted on the same rows."""
    if model.fitted is docs:
        return model.corpus
    return counted(docs, docs.sparkSession.sparkContext.broadcast(model.terms))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """``doc_id, score, evidence, terms`` for every row of ``docs(doc_id, text)``."""
    schema = f"doc_id long, {RESULT}"
    ship(docs.sparkSession)
    arrow = to_arrow_schema(T._parse_datatype_string(schema))

    def work(model, known, batch):
        rows = [_score(model, known, m, c) for m, c in zip(batch.column("mark").to_pylist(), batch.column("counts").to_pylist())]
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array([r[j] for r in rows], arrow.field(j + 1).type) for j in range(3)]], schema=arrow)

    return _votes(_of(docs, model), model, work, schema)


def without(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose text scores below the threshold, all their columns untouched; only rows that may be rejected are compared with the rejected texts' marks."""

    def work(model, known, batch):
        marks = batch.column("mark")
        out = [_score(model, known, m, c)[0] >= threshold for m, c in zip(marks.to_pylist(), batch.column("counts").to_pylist())]
        return pa.RecordBatch.from_arrays([marks.filter(pa.array(out, pa.bool_()))], ["mark"])

    ship(docs.sparkSession)
    gone = materialise(_votes(_of(docs, model).select("mark", "counts"), model, work, "mark string").distinct(), "rejected")
    model.release()
    text = F.coalesce(F.md5(F.col("text").cast("string").cast("binary")), F.lit(""))
    carried = Carried(docs, mark=text)
    return drop_rows(carried.rows, gone, "mark").select(*carried.back())


def predict(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, **parameters) -> DataFrame:
    """Fit and score: doc_id, held_out, score, predicted, evidence and the (at most 20) heaviest terms of the text."""
    scored = score(docs, fit(docs, labels, **parameters))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "evidence", "terms")
