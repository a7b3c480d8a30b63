"""Methods that clean labels rather than find copies: by similarity graphs, by reference sets, by accompanying text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions import arithmetic
from ..plans.components import connected
from ..plans.storage import materialise
from .resolve import fixed, pair_scores, spanning

MAX_CENTRES = 100_000


def _labelled(corpus: DataFrame, features: DataFrame) -> tuple[DataFrame, DataFrame]:
    have = features.where("vec is not null").select("image_id", "vec")
    return corpus.where("subject is not null").select(F.col("subject").alias("component"), "image_id").join(have.select("image_id"), "image_id", "left_semi"), have


def subject_graph(corpus: DataFrame, features: DataFrame, edge_tau: float | None = None) -> DataFrame:
    """Edges ``subject, u, v, score`` inside each label, pruned below ``edge_tau``. A large label's pairs are made in tiles, so that none is one task's work."""
    edges = pair_scores(*_labelled(corpus, features), least=None if edge_tau is None else fixed(edge_tau))
    return edges.select(F.col("component").alias("subject"), F.col("a").alias("u"), F.col("b").alias("v"), "score")


def spanning_graph(corpus: DataFrame, features: DataFrame, edge_tau: float) -> DataFrame:
    """Edges ``u, v`` that connect what the edges of ``subject_graph`` connect, at most one an image and tile: enough for components."""
    return spanning(*_labelled(corpus, features), fixed(edge_tau))


def communities(edges: DataFrame, how: str = "components", min_size: int = 3, rounds: int = 8) -> DataFrame:
    """``community, image_id`` of at least ``min_size``. ``label_propagation``: fixed rounds, heaviest label wins, ties to the smaller one."""
    if how == "components":
        found = connected(edges).select(F.col("component").alias("community"), F.col("node").alias("image_id"))
    else:
        both = materialise(edges.select("u", "v", "score").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "score")), "graph")
        label = both.select(F.col("u").alias("node")).distinct().withColumn("label", F.col("node"))
        for _ in range(rounds):
            votes = both.join(label, both["v"] == label["node"]).groupBy(F.col("u").alias("node"), "label").agg(F.sum("score").alias("w"))
            label = materialise(votes.groupBy("node").agg(F.max(F.struct("w", (-F.col("label")).alias("m"))).alias("x")).select("node", (-F.col("x.m")).alias("label")), "labels")
        found = label.select(F.col("label").alias("community"), F.col("node").alias("image_id"))
    large = found.groupBy("community").agg(F.count("*").alias("n")).where(F.col("n") >= min_size).select("community")
    return found.join(large, "community", "left_semi")


def centres(members: DataFrame, features: DataFrame) -> DataFrame:
    """Sum of the members' vectors; cosines do not ask for its length."""
    flat = members.join(features.where("vec is not null").select("image_id", "vec"), "image_id").select("community", F.posexplode("vec").alias("d", "x"))
    sums = flat.groupBy("community", "d").agg(F.sum("x").alias("x"))
    return sums.groupBy("community").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "x"))), lambda p: p["x"]).alias("centre"))


def reassign(rest: DataFrame, members: DataFrame, features: DataFrame, assign_tau: float) -> DataFrame:
    """Remaining images join the most similar community centre from ``assign_tau`` on. Centres are broadcast after a check of their number; beyond it the rest is compared in shuffled blocks."""
    c = materialise(centres(members, features), "centres")
    n = c.count()
    left = rest.select("image_id").join(features.where("vec is not null").select("image_id", "vec"), "image_id")
    if n <= MAX_CENTRES:
        pairs = left.join(F.broadcast(c))
    else:
        lots = -(-n // MAX_CENTRES)
        cut = c.withColumn("lot", F.pmod(F.xxhash64("community"), F.lit(lots)))
        pairs = left.withColumn("lot", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(lots - 1).cast("long")))).join(cut, "lot")
    best = pairs.groupBy("image_id").agg(F.max(F.struct(arithmetic.score(F.col("vec"), F.col("centre")).alias("score"), (-F.col("community")).alias("m"))).alias("x"))
    return best.where(F.col("x.score") >= fixed(assign_tau)).select("image_id", (-F.col("x.m")).alias("community"), F.col("x.score").alias("score"))


def graph_clean(corpus: DataFrame, features: DataFrame, edge_tau: float, min_size: int, assign_tau: float, community: str = "components") -> DataFrame:
    """Cleaned labels ``image_id, community, how``: retained by a large community, or assigned to one afterwards; others are dropped."""
    edges = (spanning_graph if community == "components" else subject_graph)(corpus, features, edge_tau)
    kept = materialise(communities(edges, community, min_size), "communities")
    rest = corpus.join(kept.select("image_id"), "image_id", "left_anti")
    added = reassign(rest, kept, features, assign_tau)
    return kept.select("image_id", "community", F.lit("retained").alias("how")).unionByName(added.select("image_id", "community", F.lit("assigned").alias("how")))


def reference_set(images: DataFrame, rank: Column | None = None) -> DataFrame:
    """Images with a quality above their subject's mean; where a search rank is known, it has to be in the better half as well."""
    own = Window.partitionBy("subject")
    rows = images.withColumn("_mean", F.avg("q").over(own))
    ok = F.col("q") > F.col("_mean")
    if rank is not None:
        rows = rows.withColumn("_r", F.percent_rank().over(own.orderBy(rank)))
        ok &= F.col("_r") <= 0.5
    return rows.where(ok).select("image_id", "subject", "vec", "q")


def ladder(q: Column) -> Column:
    """Acceptance threshold by quality: the worse the image, the more similar it must be."""
    return F.when(q < 2, F.lit(fixed(0.70))).when(q < 4, F.lit(fixed(0.60))).otherwise(F.lit(fixed(0.50)))


def reference_clean(images: DataFrame, tau=ladder, rank: Column | None = None) -> DataFrame:
    """``image_id, decision, mean``: reference images stay, the others stay if their mean similarity to the reference reaches tau(q)."""
    ref = materialise(reference_set(images, rank), "reference")
    others = images.join(ref.select("image_id"), "image_id", "left_anti")
    pairs = others.select("image_id", "subject", "vec", "q").join(ref.select("subject", F.col("vec").alias("rv")), "subject", "left")
    means = pairs.withColumn("s", arithmetic.score(F.col("vec"), F.col("rv"))).groupBy("image_id", "q").agg((F.sum("s").cast("double") / F.count("s")).alias("mean"))
    judged = means.select("image_id", F.when(F.coalesce(F.col("mean") >= tau(F.coalesce("q", F.lit(-1.0))), F.lit(False)), "keep").otherwise("discard").alias("decision"), "mean")
    return ref.select("image_id", F.lit("reference").alias("decision"), F.lit(None).cast("double").alias("mean")).unionByName(judged)


def text_labels(corpus: DataFrame, names: DataFrame, tokens: Column) -> DataFrame:
    """``image_id, label, weight``: how often each candidate name occurs in the accompanying text; an equi join of tokens with names."""
    found = corpus.select("image_id", F.explode(tokens).alias("name")).join(names.select("name").distinct(), "name")
    return found.groupBy("image_id", F.col("name").alias("label")).agg(F.count("*").alias("weight"))


def settle_labels(initial: DataFrame, edges: DataFrame, rounds: int = 2) -> DataFrame:
    """``image_id, label``: each image's own candidates plus its neighbours' current labels vote, in fixed rounds. ``edges(u, v)``; an image may have several candidates (several faces)."""

    def best(votes: DataFrame) -> DataFrame:
        return votes.groupBy("image_id", "label").agg(F.sum("weight").alias("w")).groupBy("image_id").agg(F.min(F.struct((-F.col("w")).alias("w"), "label")).alias("x")).select("image_id", F.col("x.label").alias("label"))

    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct()
    now = materialise(best(initial), "labels")
    for _ in range(rounds):
        near = both.join(now, both["v"] == now["image_id"]).select(F.col("u").alias("image_id"), "label", F.lit(2).cast("long").alias("weight"))
        now = materialise(best(initial.unionByName(near)), "labels")
    return now
