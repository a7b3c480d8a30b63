"""Scores of pairs in tiles of matrix products against plain arithmetic."""

import math
import random

import numpy as np

from twinfold.operators import baselines as base, resolve as res
from twinfold.plans.components import connected
from twinfold.sources import images


def _made(spark, size):
    rng = random.Random(3)
    vecs = {i: [rng.randrange(-size, size) for _ in range(8)] for i in range(60)} | {60: None, 61: [0] * 8, 62: [1, 2], 63: [1] + [None] * 7}
    comps = spark.createDataFrame([(i, i % 3) for i in vecs], "image_id long, component long")
    return vecs, comps, spark.createDataFrame(list(vecs.items()), "image_id long, vec array<long>")


def _plain(x, y):
    if not x or not y or len(x) != len(y) or None in x + y or not any(x) or not any(y):
        return None
    dot = lambda p, q: float(sum(a * b for a, b in zip(p, q)))
    return math.floor(dot(x, y) / (math.sqrt(dot(x, x)) * math.sqrt(dot(y, y))) * 2**20 + 0.5)


def test_scores_least_and_spanning_edges(spark):
    """Small numbers go through double precision, large ones through integers; tiles of any width give the same."""
    for size in (100, 1 << 29):
        vecs, comps, features = _made(spark, size)
        want = {(i % 3, i, j): _plain(vecs[i], vecs[j]) for i in vecs for j in vecs if i < j and i % 3 == j % 3}
        for chunk in (5, 1024):
            got = {(r["component"], r["a"], r["b"]): r["score"] for r in res.pair_scores(comps, features, chunk).collect()}
            assert got == want
        least = 300_000
        strong = {(a, b) for (_, a, b), s in want.items() if s is not None and s >= least}
        assert {(r["a"], r["b"]) for r in res.pair_scores(comps, features, 7, least).collect()} == strong
        edges = res.spanning(comps, features, least, 7)
        listed = spark.createDataFrame(sorted(strong), "u long, v long")
        assert sorted(map(tuple, connected(edges).collect())) == sorted(map(tuple, connected(listed).collect()))


def test_features_do_not_pass_through_the_driver(spark, tmp_path):
    """Arrays count as one number in the planner's sizes, so that it took features for small."""
    _, comps, features = _made(spark, 100)
    features.write.parquet(f"{tmp_path}/f")
    plan = res.pair_scores(comps, spark.read.parquet(f"{tmp_path}/f"))._jdf.queryExecution().executedPlan().toString()
    assert not [x for x in plan.splitlines() if "BroadcastExchange" in x and "vec" in x] and "SortMergeJoin" in plan


def test_graph_clean_by_components(spark):
    _, comps, features = _made(spark, 100)
    corpus = comps.select("image_id", comps["component"].cast("string").alias("subject"))
    got = base.graph_clean(corpus, features, 0.3, 3, 2.0)
    want = base.communities(base.subject_graph(corpus, features, 0.3), min_size=3)
    assert sorted((r["image_id"], r["community"]) for r in got.collect()) == sorted((r["image_id"], r["community"]) for r in want.collect())


def test_few_bits_are_selected_by_hashes(spark):
    """Near regions counted hash by hash give the pairs of the full comparison, with popular hashes and with several bits; images do not travel to their tiles."""
    rng = np.random.default_rng(5)
    pool = rng.integers(-(2**62), 2**62, 40)

    def block(first, n):
        rows = [np.unique(pool[np.minimum(39, rng.geometric(0.12, k))] ^ (1 << rng.integers(0, 62, k)) * rng.integers(0, 2, k)) for k in rng.integers(0, 9, n)]
        rows.sort(key=len, reverse=True)
        return np.arange(first, first + 2 * n, 2)[rng.permutation(n)], np.array([len(r) for r in rows]), np.concatenate(rows)

    def told(parts):
        return sorted((int(a[i]), int(b[j]), int(m), int(d)) for a, b, *c in parts for i, j, m, d in zip(*c))

    x, y = block(0, 90), block(1, 70)
    for limit, cutoff in ((0, 1), (1, 3), (3, 2)):
        for other in (x, y):
            want = told(images._compared(x, other, other is x, limit, cutoff))
            assert want and told(images._selected(x, other, other is x, limit, cutoff)) == want
    hashed = spark.createDataFrame([(i, [int(v) for v in pool[rng.integers(0, 40, 4)]]) for i in range(50)], "image_id long, segments array<long>")
    plan = images.segment_matches(hashed, 2, 0.03, 16)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan
