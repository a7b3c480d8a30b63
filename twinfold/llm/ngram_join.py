"""N-gram Jaccard self-join by chosen paths, exact on what the paths bring together.

Shingles are runs of five words (words: ``\\w+`` of the lower-cased text); a text of one to four words is one shingle. Documents with equal
shingle sets form a class, and one of each class goes on. Its MinHash coordinates are the shared tokens that paths choose:

1. *Split.* A tree node owns a bucket of sets and picks a few coordinates by a hash of its path; the sets that agree on the coordinate's token go to
   one child. Buckets of one set vanish, small ones are leaves, and so are buckets that a further split hardly shrinks (their sets are alike).
   With two choices a node a pair at the threshold survives to a common leaf with probability p, the fixpoint of p = 1 - (1 - s p)^2; the number of runs follows
   from p and the target recall. Everything here is (path, node) rows and counts.
2. *Brute-force leaves.* Sketches inside a leaf are compared until no two unconnected sets are left uncompared; only a spanning forest of pairs above a
   slack threshold leaves the task, never the pairs. A leaf larger than a block is cut into blocks that share anchors, and what the anchors
   did not unite is compared block by block afterwards, so no leaf is capped.
3. *Exact check.* Sets united so form candidate groups. Inside these all pairs are checked on their shingles, in tiles; links are counted per set and the linked
   sets united to components.

Defined results: null, empty and word-less texts have no shingles and link with nothing, not even with each other; repeated rows and equal texts are one
class whose members all link; null doc_ids are allowed (a class id is null only if all its doc_ids are); an empty table gives an empty result;
very long texts are processed whole, in blocks of shingles. Other columns are not read.
"""

from __future__ import annotations

import hashlib
import math
import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window, functions as F

from ..plans.bitmaps import reduce_by
from ..plans.components import connected
from ..plans.storage import discard, materialise
from .shared import per_text, pieces

_GAP = re.compile(r"\W+")
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_POWERS: dict[str, np.ndarray] = {}


def _powers(name: str, base: int, n: int) -> np.ndarray:
    """base**0 ... base**(n-1) modulo 2**64, grown by doubling."""
    own = _POWERS.get(name, np.ones(1, np.uint64))
    while len(own) < n:
        own = np.concatenate([own, own * np.uint64(pow(base, len(own), 1 << 64))])
    _POWERS[name] = own
    return own[:n]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _runs(flat: str, words: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the runs of ``words`` words in words with single spaces between them: differences of one running polynomial over the bytes."""
    raw = np.frombuffer(flat.encode("utf-8", "surrogatepass"), np.uint8)
    gaps = np.flatnonzero(raw == 32)
    starts, ends = np.concatenate([[0], gaps + 1]), np.concatenate([gaps, [len(raw)]])
    k = min(words, len(starts))
    a, b = starts[: len(starts) - k + 1], ends[k - 1 :]
    run = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * _powers("up", _BASE, len(raw)), out=run[1:])
    return np.unique(_mixed((run[b] - run[a]) * _powers("down", _INVERSE, len(raw))[a]))


def shingle_hashes(text: str | None, words: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's shingles. A very long text goes piece by piece, each with the last words of the one before, so that only its hashes grow with it."""
    out, tail, full = [], "", False
    for piece in pieces(text):
        flat = _GAP.sub(" ", piece.lower()).strip()
        if not flat:
            continue
        flat = f"{tail} {flat}" if tail else flat
        last = flat.rsplit(" ", words - 1)
        if len(last) == words:  # that many words at least
            full = True
            out.append(_runs(flat, words))
            tail = " ".join(last[1:])
        else:
            tail = flat
    if not full:
        return _runs(tail, words) if tail else np.zeros(0, np.uint64)
    return out[0] if len(out) == 1 else np.unique(np.concatenate(out))


def _lines(coordinates: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 1 << 63, coordinates, np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 1 << 63, coordinates, np.uint64)


def sketch(hashes: np.ndarray, lines: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """MinHash coordinates, block by block so that a very long text needs bounded memory."""
    a, b = lines
    low = np.full(len(a), (1 << 64) - 1, np.uint64)
    for i in range(0, len(hashes), 4096):
        part = hashes[i : i + 4096, None] * a + b
        low = np.minimum(low, part.min(axis=0))
    return low


def runs_for(threshold: float, choices: int, recall: float) -> int:
    """Runs until the target recall for a pair exactly at the threshold."""
    p = 1.0
    for _ in range(200):
        p = 1 - (1 - threshold * p) ** choices
    return max(1, math.ceil(math.log(1 - recall) / math.log(max(1e-12, 1 - p))))


def _whole_groups(batches, keys: list[str], work):
    """Runs of equal keys in sorted batches, put together across batch ends."""
    held: list[pd.DataFrame] = []
    for pdf in batches:
        if not len(pdf):
            continue
        pdf = pd.concat([*held, pdf], ignore_index=True) if held else pdf
        same = np.ones(len(pdf), bool)
        for k in keys:
            same &= (pdf[k] == pdf[k].iloc[-1]).to_numpy()
        cut = int(np.flatnonzero(~same)[-1]) + 1 if not same.all() else 0
        held = [pdf.iloc[cut:]]
        if cut:
            yield from _groups(pdf.iloc[:cut], keys, work)
    if held:
        yield from _groups(held[0], keys, work)


def _groups(pdf: pd.DataFrame, keys: list[str], work):
    change = np.zeros(len(pdf), bool)
    change[0] = True
    for k in keys:
        v = pdf[k].to_numpy()
        change[1:] |= v[1:] != v[:-1]
    bounds = [*np.flatnonzero(change), len(pdf)]
    columns = {c: pdf[c].to_numpy() for c in pdf.columns}
    out = [r for a, b in zip(bounds, bounds[1:]) if b - a > 1 and (r := work({c: v[a:b] for c, v in columns.items()})) is not None]
    if out:
        yield pd.concat(out, ignore_index=True)


class _Forest:
    def __init__(self, n: int):
        self.label = np.arange(n)
        self.edges: list[tuple[int, int]] = []

    def unite(self, i: int, others: np.ndarray) -> None:
        for j in others:
            if self.label[j] != self.label[i]:
                self.edges.append((i, int(j)))
                self.label[self.label == self.label[j]] = self.label[i]


def root_paths(low: np.ndarray, runs: int, choices: int) -> np.ndarray:
    """Tokens of the runs' first splits at full width; deeper splits and comparisons make do with 16 bits a coordinate."""
    which = np.random.default_rng(runs * 31 + choices).permutation(len(low))[np.arange(runs * choices) % len(low)]
    return _mixed(low[which] + _powers("root", _BASE, runs * choices)).astype(np.int64)


def _leaf_edges(need: int):
    """Spanning forest of a leaf's sketch pairs that agree on ``need`` coordinates; pairs already connected are not compared.
    ``side``: 0 and 1 are compared with each other only, 2 with everything."""

    def work(g: dict[str, np.ndarray]) -> pd.DataFrame | None:
        s = np.frombuffer(b"".join(g["sig"]), "<u2").reshape(len(g["node"]), -1)
        side, forest = g["side"], _Forest(len(s))
        for i in range(len(s) - 1):
            rest = np.flatnonzero(forest.label[i + 1 :] != forest.label[i]) + i + 1
            if side[i] != 2:
                rest = rest[side[rest] != side[i]]
            while len(rest):
                block, rest = rest[:4096], rest[4096:]
                forest.unite(i, block[(s[block] == s[i]).sum(axis=1) >= need])
        if not forest.edges:
            return None
        a, b = np.array(forest.edges).T
        return pd.DataFrame({"u": g["node"][a], "v": g["node"][b]})

    return work


def _tile_links(threshold: float):
    """Exact links inside a tile: how many documents each set links to, and the smallest set of its component in the tile."""

    def work(g: dict[str, np.ndarray]) -> pd.DataFrame | None:
        sets = [np.frombuffer(x, "<u8") for x in g["shingles"]]
        m, sizes = len(sets), np.array([len(x) for x in sets])
        if m <= 6:
            inter = np.zeros((m, m))
            for i in range(m):
                for j in range(i + 1, m):
                    inter[i, j] = inter[j, i] = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
        else:
            owner = np.repeat(np.arange(m), sizes)
            _, token, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
            shared = times[token] > 1
            _, token = np.unique(token[shared], return_inverse=True)
            owner, inter = owner[shared], np.zeros((m, m), np.float32)
            for lo in range(0, int(token.max(initial=-1)) + 1, 8192):
                here = (token >= lo) & (token < lo + 8192)
                has = np.zeros((m, 8192), np.float32)
                has[owner[here], token[here] - lo] = 1
                inter += has @ has.T
        link = inter >= threshold * (sizes[:, None] + sizes - inter) - 1e-9
        np.fill_diagonal(link, False)
        if g["lo"][0] != g["hi"][0]:
            link &= g["chunk"][:, None] != g["chunk"]
        forest = _Forest(m)
        for i in range(m):
            forest.unite(i, np.flatnonzero(link[i]))
        low = pd.Series(g["node"]).groupby(forest.label).transform("min").to_numpy()
        return pd.DataFrame({"node": g["node"], "root": low, "links": link @ g["copies"].astype(np.int64)})

    return work


def near_duplicates(
    docs: DataFrame, threshold: float = 0.8, words: int = 5, recall: float = 0.999, choices: int = 2, coordinates: int = 128,
    leaf: int = 96, block: int = 1024, max_depth: int = 12, seed: int = 17, slack: float = 0.15,
) -> DataFrame:
    """One row per document of ``docs(doc_id, text)``: ``doc_id, class_id, n_links, copies, kept``.

    ``class_id`` is the smallest doc_id of the connected component, ``n_links`` the number of other documents with similarity of at least ``threshold``,
    ``copies`` the number of documents with the same shingle set, itself included; ``kept`` marks one document of each component.
    """
    lines = _lines(coordinates, seed)
    runs = runs_for(threshold, choices, recall)

    def sign(texts: list) -> dict[str, list]:
        out: dict[str, list] = {k: [] for k in ("fp1", "fp2", "n", "roots", "sig")}
        for text in texts:
            h = shingle_hashes(text, words)
            d = np.frombuffer(hashlib.blake2b(h.tobytes(), digest_size=16).digest(), "<i8")
            low = sketch(h, lines) if len(h) else None
            out["fp1"].append(int(d[0])), out["fp2"].append(int(d[1])), out["n"].append(len(h))
            out["roots"].append([] if low is None else root_paths(low, runs, choices).tolist())
            out["sig"].append(b"" if low is None else (low >> np.uint64(48)).astype("<u2").tobytes())
        return out

    text = F.col("text").cast("string")
    hashed = {"t1": F.xxhash64(text), "t2": F.xxhash64(F.lit(5), text)}
    read = docs.select(text.alias("text"), *[c.alias(k) for k, c in hashed.items()])
    signed = per_text(docs, lambda: sign, "fp1 long, fp2 long, n int, roots array<long>, sig binary", hashed)
    all_ = materialise(signed.withColumn("uid", F.monotonically_increasing_id()), "signed")
    classes = all_.where("n > 0").groupBy("fp1", "fp2").agg(F.min(F.struct("uid", "t1", "t2")).alias("r"), F.count("*").alias("copies"), F.min("doc_id").alias("first_id"))
    classes = materialise(classes.select("fp1", "fp2", F.col("r.uid").alias("node"), "r.t1", "r.t2", "copies", "first_id"), "classes")
    found = _candidates(all_, classes, threshold, choices, coordinates, leaf, block, max_depth, slack)
    groups = connected(found)
    tiles = _tiles(read, classes, materialise(groups, "groups"), block // 2, words)
    checked = materialise(
        tiles.mapInPandas(lambda it, f=_tile_links(threshold): _whole_groups(it, ["component", "lo", "hi"], f), "node long, root long, links long"), "links"
    )
    linked = connected(checked.select(F.col("node").alias("u"), F.col("root").alias("v")))
    links = checked.groupBy("node").agg(F.sum("links").alias("links"))
    per_class = classes.join(linked, "node", "left").join(links, "node", "left").select(
        "fp1", "fp2", "node", "copies", "first_id", F.coalesce("component", "node").alias("component"), (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links")
    )
    names = per_class.groupBy("component").agg(F.min("first_id").alias("class_id"), F.min("node").alias("_keep"))
    final = materialise(per_class.join(names, "component").select("fp1", "fp2", "class_id", "n_links", "copies", "_keep"), "classes")
    own = all_.select("uid", "doc_id", "n", "fp1", "fp2")
    # Documents without shingles stay alone; they are not sent through the join, where they would meet in one task.
    alone = own.where("n = 0").select("doc_id", F.col("doc_id").alias("class_id"), F.lit(0).cast("long").alias("n_links"), F.lit(1).cast("long").alias("copies"), F.lit(True).alias("kept"), "uid")
    rest = own.where("n > 0").join(final, ["fp1", "fp2"]).select("doc_id", "class_id", "n_links", "copies", (F.col("uid") == F.col("_keep")).alias("kept"), "uid")
    return rest.unionByName(alone)


def _candidates(all_: DataFrame, classes: DataFrame, threshold: float, choices: int, coordinates: int, leaf: int, block: int, max_depth: int, slack: float) -> DataFrame:
    """Spanning edges (u, v) of all leaves of all runs, verified by sketch."""
    need = math.ceil((threshold - slack) * coordinates)
    own = classes.select("node")
    # The runs are the root's children; all runs go down together.
    roots = all_.where("n > 0").select(F.col("uid").alias("node"), "roots").join(own, "node", "left_semi")
    step = roots.select("node", F.lit(None).cast("long").alias("was"), F.posexplode("roots").alias("i", "path")).select("node", "was", F.xxhash64("i", "path").alias("path"))
    leaves: list[DataFrame] = []
    live = None
    for depth in range(max_depth):
        step = materialise(step.dropDuplicates(["path", "node"]) if depth else step, "step")
        # A table of its own: the join with it has two plain exchanges, and a bucket with very many sets is split.
        sizes = materialise(step.groupBy("path").agg(F.count("*").alias("size"), F.first("was").alias("was")).where("size > 1"), "sizes")
        done = (F.col("size") <= leaf) | (F.col("size") >= 0.8 * F.coalesce("was", F.lit(1 << 60))) | F.lit(depth == max_depth - 1)
        rows = materialise(step.select("node", "path").join(sizes.select("path", "size", done.alias("leaf")), "path"), "buckets")
        discard(step, sizes)
        if not depth:  # most sets meet nobody; their sketches are read no more
            nodes = rows.select("node").distinct()
            sketches = all_.where("n > 0").select(F.col("uid").alias("node"), "sig")
            live = materialise(reduce_by(sketches, nodes, "node").join(nodes, "node", "left_semi"), "live")
        leaves.append(rows.where("leaf"))
        if not rows.where("not leaf").limit(1).count():
            break
        picks = F.array(*[F.pmod(F.xxhash64("path", F.lit(c)), F.lit(coordinates)).cast("int") for c in range(choices)])
        step = (
            rows.where("not leaf").join(live, "node").select("node", "path", "size", "sig", F.explode(picks).alias("i"))
            .select("node", F.col("size").alias("was"), F.xxhash64("path", "i", F.expr("substring(sig, 2 * i + 1, 2)")).alias("path"))
        )
    rows = leaves[0]
    for more in leaves[1:]:
        rows = rows.unionByName(more)
    keys = ["path", "lo", "hi"]

    def compared(part: DataFrame) -> DataFrame:
        spread = part.repartition(*keys).sortWithinPartitions(*keys)
        return spread.select(*keys, "node", "side", "sig").mapInPandas(lambda it, f=_leaf_edges(need): _whole_groups(it, keys, f), "u long, v long")

    # Blocks by a hash of the set; the sets of smallest hash of a large leaf are anchors and go to all its blocks.
    blocks = F.ceil(F.col("size") / block).cast("int")
    mine = F.pmod(F.xxhash64("node", "path"), F.col("blocks")).cast("int")
    small = rows.where(F.col("size") <= block).select("path", F.lit(0).alias("lo"), F.lit(0).alias("hi"), "node", F.lit(2).alias("side"))
    large = materialise(rows.where(F.col("size") > block).withColumn("blocks", blocks).withColumn("mine", mine), "large")
    if not large.limit(1).count():
        return materialise(compared(small.join(live, "node")), "edges")
    weight = F.pmod(F.xxhash64("node", F.lit("anchor")), F.col("size"))
    anchors = large.where(weight < 16).select("path", "node", "mine", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("lo")).where("lo <> mine")
    first = large.select("path", F.col("mine").alias("lo"), F.col("mine").alias("hi"), "node", F.lit(2).alias("side"))
    first = first.unionByName(anchors.select("path", "lo", F.col("lo").alias("hi"), "node", F.lit(2).alias("side")))
    edges = materialise(compared(small.unionByName(first).join(live, "node")), "edges")
    # What a large leaf's anchors left apart from its largest component is compared with all of its blocks.
    named = large.join(connected(edges), "node", "left").withColumn("component", F.coalesce("component", "node"))
    named = materialise(named, "named")
    most = named.groupBy("path", "component").agg(F.count("*").alias("k")).groupBy("path").agg(F.max_by("component", F.struct("k", "component")).alias("most"))
    apart = named.join(most, "path").where("component <> most")
    if not apart.limit(1).count():
        return edges
    per = apart.groupBy("path").agg(F.ceil(F.count("*") / block).cast("int").alias("lots"))
    lots = apart.join(per, "path").withColumn("lo", F.pmod(F.xxhash64("node"), F.col("lots")).cast("int"))
    ends = F.col("lots") - 1
    left = lots.select("path", "lo", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("hi"), "node", F.lit(0).alias("side"))
    stay = named.join(per, "path").join(apart.select("path", "node"), ["path", "node"], "left_anti")
    right = stay.select("path", F.explode(F.sequence(F.lit(0), ends)).alias("lo"), F.col("mine").alias("hi"), "node", F.lit(1).alias("side"))
    # Those apart among themselves: every two lots meet once, under negative numbers of the second.
    meet = lots.withColumn("j", F.explode(F.sequence(F.lit(0), ends)))
    side = F.when(F.col("lo") == F.col("j"), 2).when(F.col("lo") < F.col("j"), 0).otherwise(1)
    cross = meet.select("path", F.least("lo", "j").alias("lo"), (-1 - F.greatest("lo", "j")).alias("hi"), "node", side.alias("side"))
    return materialise(edges.unionByName(compared(left.unionByName(right).unionByName(cross).join(live, "node"))), "edges")


def _tiles(read: DataFrame, classes: DataFrame, groups: DataFrame, block: int, words: int) -> DataFrame:
    """Members of candidate groups with their shingles, dealt to tiles: (component, lo, hi) holds chunks lo and hi of a group.

    Shingles are not kept from the first pass; the few texts that came together are read again, found by the hash of the text.
    """
    sizes = groups.groupBy("component").agg(F.ceil(F.count("*") / block).cast("int").alias("chunks"))
    members = groups.join(sizes, "component").join(classes.select("node", "copies", "t1", "t2"), "node")
    members = materialise(members.withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")), "members")
    texts = reduce_by(read.select("t1", "t2", "text"), members.select("t1"), "t1").groupBy("t1", "t2").agg(F.first("text").alias("text"))

    def sets(batches):
        for pdf in batches:
            yield pdf[["t1", "t2"]].assign(shingles=[shingle_hashes(t, words).astype("<u8").tobytes() for t in pdf["text"]])

    keys = ["component", "lo", "hi"]
    dealt = members.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).select(
        "component", F.least("chunk", "other").alias("lo"), F.greatest("chunk", "other").alias("hi"), "node", "copies", "chunk", "t1", "t2"
    )
    with_sets = dealt.join(texts.mapInPandas(sets, "t1 long, t2 long, shingles binary"), ["t1", "t2"])
    return with_sets.repartition(*keys).sortWithinPartitions(*keys).select(*keys, "node", "copies", "chunk", "shingles")
