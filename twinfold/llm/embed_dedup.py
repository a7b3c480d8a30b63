"""Near-duplicate vectors by a subspace pigeonhole join.

For unit vectors cosine >= t means a squared distance of at most 2(1-t). After a random rotation the coordinates are split into blocks; if the whole distance keeps its
budget, some block keeps its proportional share. So each block is range-joined under its share, and the union of what the blocks find is verified exactly on the original
vectors. Vectors lie in chunks, each once and in the order of their cells (nearest pivot); a tile joins two chunks block by block, and only blocks whose balls (centre and radius of a chunk in a block)
come near enough to hold a pair in range. Tiles are a Cartesian product of the chunks' table with itself, read from its files: nothing is dealt out anew, so disk is linear in the vectors while the comparisons are not.
Links are summed without listing pairs: a tile returns, per vector, its number of links and the root of its local component.
Equal vectors are one class before all that, told by a digest of 128 bits.

Defined results: vectors that take no part (see :func:`twinfold.llm.vectors.usable`) get a row with no links and their own id; repeated ids count as one vector and give one row each; null ids give
rows with null ids; an empty table gives an empty result. Labels and other columns are not read.
"""

from __future__ import annotations

import hashlib
import math
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..plans.components import connected
from ..plans.shipping import ship
from ..plans.storage import discard, materialise
from .vectors import least_of_each_id, matrix, pivots, rotation, sound

CHUNK = "id long, nodes binary, copies binary, v binary, centre array<double>, radii array<double>"
STRIPE = 256


class Subspaces:
    """Rotation, blocks of columns, the share of the distance that each block may use, and the pivots that order vectors."""

    def __init__(self, sample: np.ndarray, threshold: float, blocks: int, cells: int, seed: int = 23):
        self.dim = sample.shape[1]
        self.turn = rotation(self.dim, seed)
        self.columns = [c for c in np.array_split(np.arange(self.dim), min(blocks, self.dim)) if len(c)]
        self.budget = [2 * (1 - threshold) * len(c) / self.dim + 1e-9 for c in self.columns]
        self.pivots = pivots(sample / np.sqrt((sample * sample).sum(1))[:, None], cells, seed)

    def turned(self, raw: np.ndarray) -> np.ndarray:
        return (raw / np.sqrt((raw * raw).sum(1))[:, None]) @ self.turn

    def cells(self, raw: np.ndarray) -> np.ndarray:
        """Nearest pivots; column after column, so that equal vectors get the same cell in every batch."""
        norm, far = np.zeros(len(raw)), np.zeros((len(raw), len(self.pivots)))
        for c in range(self.dim):
            norm += raw[:, c] ** 2
        unit = raw / np.sqrt(norm)[:, None]
        for c in range(self.dim):
            far += (unit[:, c, None] - self.pivots[:, c]) ** 2
        return far.argmin(axis=1)


def _vectors(batch: pa.RecordBatch, dim: int) -> np.ndarray:
    """The column ``v``; negative zeros are zeros."""
    return batch.column("v").flatten().to_numpy(zero_copy_only=False).reshape(-1, dim) + 0.0


def _digests(raw: np.ndarray) -> list[bytes]:
    return [hashlib.blake2b(x.tobytes(), digest_size=16).digest() for x in raw]


def _classes(keys: list[bytes], nodes: np.ndarray, copies: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(a row of each class, its smallest node, its copies) of rows sorted by their digests."""
    k = np.frombuffer(b"".join(keys), "S16")
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    return first, np.minimum.reduceat(nodes, first), np.add.reduceat(copies, first)


def _named(rows: DataFrame, dim: int) -> DataFrame:
    """``vec_id, key``: the digest of each vector."""

    def work(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pa.array(_digests(_vectors(b, dim)), pa.binary())], ["vec_id", "key"])

    return rows.mapInArrow(work, "vec_id long, key binary")


def _chunked(rows: DataFrame, space: Subspaces, kind: str, parts: int, chunk: int) -> DataFrame:
    """The table of chunks: each class of equal vectors once. Copies are counted in their batch before they are dealt out by ranges of cell and digest, so that no range holds more of a class than there are batches."""

    def deal(batches):
        for b in batches:
            if b.num_rows:
                raw = _vectors(b, space.dim)
                keys = _digests(raw)
                order = sorted(range(len(keys)), key=keys.__getitem__)
                first, nodes, copies = _classes([keys[i] for i in order], b.column("vec_id").to_numpy()[order], np.ones(len(order), np.int64))
                own = np.array(order)[first]
                cells = space.cells(raw[own])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(cells.astype(np.int32)), pa.array([keys[i] for i in own], pa.binary()), pa.array(nodes), pa.array(copies), pa.array([x.tobytes() for x in raw[own].astype(kind)], pa.binary())], ["cell", "key", "node", "copies", "v"]
                )

    def row(keys, nodes, copies, blobs):
        first, nodes, copies = _classes(keys, nodes, copies)
        for s in range(0, len(first), chunk):
            v = np.frombuffer(b"".join(blobs[i] for i in first[s : s + chunk]), kind).reshape(-1, space.dim)
            turned = space.turned(v.astype(np.float64))
            centre = turned.mean(axis=0)
            off = (turned - centre) ** 2
            radii = [math.sqrt(off[:, c].sum(1).max()) + 1e-6 for c in space.columns]
            own = nodes[s : s + chunk]
            yield [int(own.min()), own.astype("<i8").tobytes(), copies[s : s + chunk].astype("<i8").tobytes(), v.tobytes(), centre.tolist(), radii]

    def pack(batches):
        held: list = [[], np.zeros(0, np.int64), np.zeros(0, np.int64), []]
        for b in batches:
            held = [held[0] + b.column("key").to_pylist(), np.append(held[1], b.column("node").to_numpy()), np.append(held[2], b.column("copies").to_numpy()), held[3] + b.column("v").to_pylist()]
            classes = np.flatnonzero(np.array([x != y for x, y in zip(held[0][1:], held[0])], bool)) + 1  # where later classes begin
            if whole := len(classes) // chunk * chunk:
                end = int(classes[whole - 1])
                yield batch(row(*(h[:end] for h in held)))
                held = [h[end:] for h in held]
        if held[0]:
            yield batch(row(*held))

    def batch(found):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found), (pa.int64(), *[pa.binary()] * 3, *[pa.list_(pa.float64())] * 2))], [x.split()[0] for x in CHUNK.split(", ")])

    dealt = rows.mapInArrow(deal, "cell int, key binary, node long, copies long, v binary")
    return dealt.repartitionByRange(parts, "cell", "key").sortWithinPartitions("cell", "key").mapInArrow(pack, CHUNK)


def _reach(space: Subspaces, j: int, a: Column, b: Column) -> Column:
    """Whether the balls of two chunks in block ``j`` can hold a pair within its share; ``a`` and ``b`` are structs of centre and radii."""
    at, n = int(space.columns[j][0]) + 1, len(space.columns[j])
    apart = F.zip_with(F.slice(a["centre"], at, n), F.slice(b["centre"], at, n), lambda x, y: (x - y) * (x - y))
    room = a["radii"][j] + b["radii"][j] + F.lit(math.sqrt(space.budget[j]) + 1e-6)
    return F.aggregate(apart, F.lit(0.0), lambda s, x: s + x) <= room * room


def _linker(space: Subspaces, threshold: float, kind: str):
    def load(nodes, copies, v, blocks):
        raw = np.frombuffer(v, kind).reshape(-1, space.dim).astype(np.float64)
        turned = space.turned(raw)
        sides = {j: turned[:, space.columns[j]] for j in blocks}
        return np.frombuffer(nodes, "<i8"), np.frombuffer(copies, "<i8"), raw, np.sqrt((raw * raw).sum(1)), sides

    def pairs(x: tuple, y: tuple, same: bool, blocks: list[int]):
        """Linked pairs (row of x, row of y) that some block finds.

        |a - b|^2 <= budget as one product in single precision: a.b - |a|^2/2 - |b|^2/2 >= -budget/2, with room for rounding; what passes is compared in double precision.
        """
        left, right, least = [], [], []
        for j in blocks:
            a, b = x[4][j], y[4][j]
            left.append(np.column_stack([a, -(a * a).sum(1) / 2, np.ones(len(a))]).astype(np.float32))
            right.append(np.ascontiguousarray(np.column_stack([b, np.ones(len(b)), -(b * b).sum(1) / 2]).astype(np.float32).T))
            least.append(np.float32(-space.budget[j] / 2 - 1e-5))
        us, vs = [], []
        out = np.empty((STRIPE, len(y[0])), np.float32)
        for lo in range(0, len(x[0]), STRIPE):
            n = min(STRIPE, len(x[0]) - lo)
            skip = lo if same else 0
            near = None
            for a, b, t in zip(left, right, least):
                made = np.matmul(a[lo : lo + n], b[:, skip:], out=out[:n, : len(y[0]) - skip] if not skip else None)
                hit = np.flatnonzero(made.max(axis=1) >= t)
                if len(hit):
                    if near is None:
                        near = np.zeros(made.shape, bool)
                    near[hit] |= made[hit] >= t
            if near is None:
                continue
            if same:
                near &= np.arange(n)[:, None] < np.arange(near.shape[1])
            at = np.flatnonzero(near)
            for s in range(0, len(at), 100_000):
                a, b = np.divmod(at[s : s + 100_000], near.shape[1])
                a, b = a + lo, b + skip
                ok = np.einsum("ij,ij->i", x[2][a], y[2][b]) / (x[3][a] * y[3][b]) >= threshold
                if ok.any():
                    us.append(a[ok])
                    vs.append(b[ok])
        return us, vs

    def tile(x: tuple, y: tuple, us: list, vs: list):
        a, b = np.concatenate(us), np.concatenate(vs)
        u, v = x[0][a], y[0][b]
        links = pd.concat([pd.DataFrame({"node": u, "links": y[1][b]}), pd.DataFrame({"node": v, "links": x[1][a]})]).groupby("node")["links"].sum()
        nodes = links.index.to_numpy()
        return pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(_roots(nodes, u, v)), pa.array(links.to_numpy())], ["node", "root", "links"])

    def run(batches):
        last, x = None, ()
        for batch in batches:
            for r in batch.to_pylist():
                blocks = [j for j, live in enumerate(r["live"]) if live]
                if r["a_id"] != last:
                    last, x = r["a_id"], load(r["a_nodes"], r["a_copies"], r["a_v"], range(len(space.columns)))
                same = r["a_id"] == r["b_id"]
                y = x if same else load(r["b_nodes"], r["b_copies"], r["b_v"], blocks)
                us, vs = pairs(x, y, same, blocks)
                if us:
                    yield tile(x, y, us, vs)

    return run


def _roots(nodes: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Smallest node of each node's component in the pairs (u, v); nodes are sorted."""
    label, a, b = nodes.copy(), np.searchsorted(nodes, u), np.searchsorted(nodes, v)
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        new = np.minimum(new, new[np.searchsorted(nodes, new)])
        if (new == label).all():
            return label
        label = new


def near_duplicates(table: DataFrame, threshold: float = 0.9, blocks: int = 4, sample_rows: int = 5_000, chunk: int = 4096, lot: int = 16_384, seed: int = 23) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` for every row of ``table(vec_id, embedding)``. A chunk has at most ``chunk`` vectors, a file of chunks about ``lot``."""
    spark = table.sparkSession
    ship(spark)
    rows, dim = sound(table)
    if not dim:
        return table.select(F.col("vec_id").cast("long").alias("vec_id"), F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component_id"), F.lit(True).alias("kept"))
    kind = "<f4" if isinstance(table.schema["embedding"].dataType.elementType, T.FloatType) else "<f8"
    named = materialise(_named(rows, dim), "named")
    if not named.groupBy("vec_id").count().where("count > 1").isEmpty():
        rows = materialise(least_of_each_id(rows), "vectors")
        named = materialise(_named(rows, dim), "named")
    n = named.count()
    picked = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample_rows).select("v").collect()
    space = Subspaces(matrix(r["v"] for r in picked), threshold, blocks, max(4, min(256, n // 1024)), seed)
    del picked
    chunks = materialise(_chunked(rows, space, kind, max(1, -(-n // lot)), chunk), "chunks")
    a, b = (chunks.select(*[F.col(c).alias(f"{s}_{c}") for c in ("id", "nodes", "copies", "v")], F.struct("centre", "radii").alias(f"{s}_ball")) for s in "ab")
    # either orientation of two chunks is as likely, so that all tasks of the product have work
    turn = F.xxhash64(F.least("a_id", "b_id"), F.greatest("a_id", "b_id")).bitwiseAND(1) == 0
    live = [_reach(space, j, F.col("a_ball"), F.col("b_ball")) for j in range(len(space.columns))]
    tiles = a.join(b.hint("shuffle_replicate_nl"), ((F.col("a_id") == F.col("b_id")) | ((F.col("a_id") < F.col("b_id")) == turn)) & reduce(Column.__or__, live))
    linked = materialise(tiles.select("a_id", "a_nodes", "a_copies", "a_v", "b_id", "b_nodes", "b_copies", "b_v", F.array(*live).alias("live")).mapInArrow(_linker(space, threshold, kind), "node long, root long, links long"), "links")
    discard(chunks)
    groups = connected(linked.select(F.col("node").alias("u"), F.col("root").alias("v")))
    links = linked.groupBy("node").agg(F.sum("links").alias("links"))
    classes = named.groupBy("key").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies"))
    told = classes.join(groups, "node", "left").join(links, "node", "left").select("key", F.coalesce("component", "node").alias("component_id"), (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))
    per_id = named.join(materialise(told, "told"), "key").select("vec_id", "n_links", "component_id")
    own = table.select(F.col("vec_id").cast("long").alias("vec_id"))
    done = own.join(per_id, "vec_id", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return done.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
