"""Approximate nearest neighbours by inner product: inverted lists scanned dimension block by dimension block.

Vectors are rotated at random, so that any leading block of coordinates is a fair sample of the whole, and dealt to lists by k-means pivots (rotation and pivots are fitted on a bounded
sample, every row is indexed). Inside a probed list a query's partial products over the first column blocks are extrapolated; a candidate whose extrapolation stays below the query's
current k-th best by more than a few standard errors is abandoned, the rest get their exact product on the original vectors in double precision. Queries and candidates meet in tiles, so that a block's
products are one matrix product. A query first scans its nearest list, and takes the k-th best found there into all other lists, so that these return little. The number of lists probed is measured, not guessed:
for a bounded sample of queries the true neighbours are found by brute force over all rows, and as many lists are probed as cover ``target`` of them; ``lists`` and ``probed`` in the result say how many there
are and were probed.

Defined results: see :func:`twinfold.llm.vectors.usable` for rows that take no part; ties go to the smaller id; a query with fewer candidates than k gets them all; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window, functions as F

from ..plans.shipping import ship
from ..plans.storage import materialise
from .vectors import as_matrix, distances, matrix, pivots, rotation, usable

FOUND = "query_id long, vec_id long, score double"


class Index:
    """Rotation and pivots; ``order`` ranks the lists for queries."""

    def __init__(self, sample: np.ndarray, lists: int, seed: int = 11):
        self.dim = sample.shape[1]
        self.turn = rotation(self.dim, seed)
        self.pivots = pivots(sample @ self.turn, lists, seed)

    def assign(self, x: np.ndarray) -> np.ndarray:
        return distances(x @ self.turn, self.pivots).argmin(axis=1)

    def order(self, q: np.ndarray) -> np.ndarray:
        return np.argsort(-((q @ self.turn) @ self.pivots.T), axis=1, kind="stable")


def top_pairs(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    return np.lexsort((ids, -scores))[:k]


def _scan(index: Index, k: int, columns: int, errors: float):
    """One (list, chunk): candidates come first, then queries with their thresholds, batch by batch. Tiles of 1024 candidates by 256 queries are compared a column block at a time, as matrices while most
    pairs of a tile live and pair by pair once few do."""
    dim = index.dim

    def answer(cand: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray], queries: pd.DataFrame):
        qids, raw = queries["vec_id"].to_numpy(), as_matrix(queries["v"], dim)
        norms, turned, floor = np.sqrt((raw * raw).sum(1)), raw @ index.turn, queries["floor"].to_numpy().copy()
        kept = []  # rows (query, candidate, score), at most k a query after each tile
        for lo in range(0, len(cand[0]), 1024):
            c = slice(lo, lo + 1024)
            found = tile(cand[0][c], *(x[c] for x in cand[1:]), qids, raw, turned, norms, floor)
            q, i, score = (np.concatenate(x) for x in zip(*kept, found))
            order = np.lexsort((i, -score, q))
            q, i, score = q[order], i[order], score[order]
            first = np.flatnonzero(np.diff(q, prepend=-1))
            rank = np.arange(len(q)) - np.repeat(first, np.diff(first, append=len(q)))
            last = rank == k - 1
            floor[q[last]] = np.maximum(floor[q[last]], score[last])
            ok = rank < k
            kept = [(q[ok], i[ok], score[ok])]
        return pd.DataFrame({"query_id": qids[kept[0][0]], "vec_id": kept[0][1], "score": kept[0][2]})

    def tile(ids, raw, turned, norms, qids, q_raw, q_turned, q_norms, floor):
        """(query, candidate id, exact product) of the pairs of a tile that may be among the best."""
        scale = q_norms[:, None] * norms[None, :]
        held = floor[:, None]
        # Coordinates after a random rotation are a sample of the product; its spread grows with the cosine that a pair must have to matter.
        near = np.clip(held / np.maximum(scale, 1e-300), -1, 1)
        spread = errors * scale * np.sqrt(1 + near * near)
        partial, at, pairs = np.zeros(scale.shape), 0, None
        while at < dim:
            e = min(at + columns, dim)
            if pairs is None:
                partial += q_turned[:, at:e] @ turned[:, at:e].T
            else:
                partial += np.einsum("ij,ij->i", q_turned[pairs[0], at:e], turned[pairs[1], at:e])
            at = e
            if e == dim or not (floor > -np.inf).any():
                continue
            stray = math.sqrt((1 / e) * (1 - e / dim))
            if pairs is None:
                alive = partial * (dim / e) + spread * stray >= held
                if 4 * np.count_nonzero(alive) < alive.size:
                    pairs = np.nonzero(alive)
                    partial = partial[pairs]
            else:
                alive = partial * (dim / e) + spread[pairs] * stray >= floor[pairs[0]]
                pairs, partial = (pairs[0][alive], pairs[1][alive]), partial[alive]
        if pairs is None:
            pairs = np.nonzero(np.ones(scale.shape, bool))
            partial = partial.ravel()
        alive = (partial >= floor[pairs[0]] - 1e-9) & (ids[pairs[1]] != qids[pairs[0]])
        q, i = pairs[0][alive], pairs[1][alive]
        exact = np.einsum("ij,ij->i", q_raw[q], raw[i])
        ok = exact >= floor[q]
        return q[ok], ids[i[ok]], exact[ok]

    def run(batches):
        key, held, cand = None, [], None
        for pdf in batches:
            for own, part in pdf.groupby(["list", "chunk"], sort=False):
                if own != key:
                    key, held, cand = own, [], None
                is_query = part["role"].to_numpy() == 1
                if not is_query.all():
                    held.append(part[~is_query])
                if is_query.any() and held:
                    if cand is None:
                        c = pd.concat(held)
                        raw = as_matrix(c["v"], index.dim)
                        cand = (c["vec_id"].to_numpy(), raw, raw @ index.turn, np.sqrt((raw * raw).sum(1)))
                    asked = part[is_query]
                    for lo in range(0, len(asked), 256):
                        yield answer(cand, asked.iloc[lo : lo + 256])

    return run


def search(table: DataFrame, is_query, k: int = 20, target: float = 0.95, sample_rows: int = 20_000, sample_queries: int = 128, chunk: int = 4096, columns: int = 16, errors: float = 2.5, seed: int = 11) -> DataFrame:
    """``query_id, rank, vec_id, score`` for the rows where ``is_query`` (a condition on vec_id) holds, against all rows."""
    spark = table.sparkSession
    ship(spark)
    rows, dim = usable(table)
    if not dim:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double, lists int, probed int")
    rows = materialise(rows, "vectors")
    n = rows.count()
    picked = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample_rows).collect()
    index = Index(matrix(r["v"] for r in picked), max(1, min(4096, round(math.sqrt(n) / 2))), seed)

    def assign(batches):
        for pdf in batches:
            x = matrix(pdf["v"]) if len(pdf) else np.zeros((0, dim))
            yield pd.DataFrame({"vec_id": pdf["vec_id"], "list": index.assign(x) if len(x) else [], "v": [a.astype("<f8").tobytes() for a in x]})

    listed = materialise(rows.mapInPandas(assign, "vec_id long, list int, v binary"), "lists")
    sizes = {r["list"]: r["n"] for r in listed.groupBy("list").agg(F.count("*").alias("n")).collect()}  # at most 4096 rows
    probes = _probes(listed, index, is_query, k, target, sample_queries, len(sizes))
    counts = np.array([sizes.get(i, 0) for i in range(len(index.pivots))])

    def route(batches):
        for pdf in batches:
            if len(pdf):
                order = index.order(as_matrix(pdf["v"], dim))
                enough = (np.cumsum(counts[order], axis=1) < 4 * k).sum(axis=1) + 1
                yield pd.DataFrame({"vec_id": pdf["vec_id"], "v": pdf["v"], "lists": [o[: max(probes, e)].tolist() for o, e in zip(order, enough)]})

    routed = materialise(listed.where(is_query).select("vec_id", "v").mapInPandas(route, "vec_id long, v binary, lists array<int>"), "routes")
    chunks = spark.createDataFrame([(i, -(-s // chunk)) for i, s in sizes.items()], "list int, chunks int")
    dealt = listed.join(F.broadcast(chunks), "list").select("list", F.pmod(F.xxhash64("vec_id"), "chunks").cast("int").alias("chunk"), F.lit(0).alias("role"), "vec_id", F.lit(0.0).alias("floor"), "v")
    keys = ["list", "chunk"]

    def scan(queries: DataFrame) -> DataFrame:
        asked = queries.join(F.broadcast(chunks), "list").select("list", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(1).alias("role"), "vec_id", "floor", "v")
        both = dealt.unionByName(asked).repartition(*keys).sortWithinPartitions(*keys, "role")
        return both.mapInPandas(_scan(index, k, columns, errors), FOUND)

    none = F.lit(float("-inf"))
    first = materialise(scan(routed.select("vec_id", "v", F.col("lists")[0].alias("list"), none.alias("floor"))), "first")
    ranked = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    floors = first.withColumn("rank", ranked).where(F.col("rank") == k).select(F.col("query_id").alias("vec_id"), "score")
    rest = routed.join(floors, "vec_id", "left").select("vec_id", "v", F.explode(F.slice("lists", 2, len(counts) + 1)).alias("list"), F.coalesce("score", none).alias("floor"))
    found = first.unionByName(scan(rest))
    return found.withColumn("rank", ranked.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", F.lit(len(sizes)).alias("lists"), F.lit(probes).alias("probed"))


def brute_force(listed: DataFrame, ids: np.ndarray, queries: np.ndarray, k: int) -> DataFrame:
    """Exact neighbours of a bounded set of queries over all rows, with the list of each neighbour."""

    def run(batches):
        for pdf in batches:
            if not len(pdf):
                continue
            own, s = pdf["vec_id"].to_numpy(), queries @ as_matrix(pdf["v"], queries.shape[1]).T
            s[ids[:, None] == own] = -np.inf
            for i, qid in enumerate(ids):
                at = top_pairs(s[i], own, k)
                at = at[s[i][at] > -np.inf]
                yield pd.DataFrame({"query_id": qid, "vec_id": own[at], "score": s[i][at], "list": pdf["list"].to_numpy()[at]})

    ranked = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return listed.mapInPandas(run, FOUND + ", list int").withColumn("rank", ranked).where(F.col("rank") <= k)


def _probes(listed: DataFrame, index: Index, is_query, k: int, target: float, sample_queries: int, lists: int) -> int:
    """Lists to probe so that the sampled queries' true neighbours are covered to ``target``."""
    asked = listed.where(is_query).orderBy(F.xxhash64("vec_id", F.lit(3)), "vec_id").limit(sample_queries).collect()
    if not asked:
        return 1
    ids, q = np.array([r["vec_id"] for r in asked]), as_matrix([r["v"] for r in asked], index.dim)
    place = np.argsort(index.order(q), axis=1)
    row = {int(i): j for j, i in enumerate(ids)}
    at = [int(place[row[r["query_id"]], r["list"]]) for r in brute_force(listed, ids, q, k).select("query_id", "list").collect()]
    if not at:
        return 1
    covered = np.cumsum(np.bincount(at, minlength=len(index.pivots))) / len(at)
    return int(np.searchsorted(covered, target)) + 1
