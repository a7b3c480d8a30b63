"""Connected components by alternating star contraction, as DataFrame rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .storage import discard, materialise


def _star_min(edges: DataFrame) -> DataFrame:
    """(u, v) with the smallest neighbour-or-self of u beside each edge. Sorted merge by hint: ids compress so well that the planner takes tables of any node for small and would send them through the driver."""
    low = materialise(edges.groupBy("u").agg(F.min("v").alias("m")), "lows")  # a table of its own, so that the join below has two plain exchanges and can split a hub
    return edges.join(low.hint("merge"), "u").withColumn("m", F.least("u", "m"))


def _large(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _star_min(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    near = _star_min(down)
    moved = near.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(near.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def _stars(edges: DataFrame) -> bool:
    """Whether every node is either a centre or a leaf of one centre."""
    ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(edges.select(F.col("v").alias("node"), F.lit(0).alias("out"), F.lit(1).alias("into")))
    per = ends.groupBy("node").agg(F.sum("out").alias("out"), F.max("into").alias("into"))
    return per.where("out > 1 or (out = 1 and into = 1)").isEmpty()


def connected(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` of longs to ``(node, component)`` with the smallest node as name.

    Loops, repeated and reversed edges are allowed; nodes without an edge to another node do not appear. Each round is two grouped minima and two joins on the node (hot hubs are split by the adaptive skew
    join) and ends with one grouped check whether only stars are left; disjoint sets given as stars take no round at all.
    """
    now = materialise(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    for _ in range(max_rounds):
        if _stars(now):
            break
        new = materialise(_small(_large(now)), "edges")
        discard(now)
        now = new
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
