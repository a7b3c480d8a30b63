"""What large tables asked for: batches of digests, joins that send nothing large through the driver."""

import re

import numpy as np
from pyspark.sql import functions as F

from twinfold.functions import arithmetic, segments
from twinfold.functions.blake3 import blake3, blake3_many, hex_digests
from twinfold.operators import detect as det
from twinfold.queries import methods, more_methods
from twinfold.sources import images


def test_digests_of_many_inputs_side_by_side():
    data = [bytes(i % 251 for i in range(n)) for n in (0, 1, 64, 1023, 1024, 1025, 2048, 3073, 5000, 31745)]
    assert blake3_many(data) == [blake3(x) for x in data] and blake3_many([]) == []
    assert hex_digests([data[3], None, data[0]]) == [blake3(data[3]).hex(), None, blake3(b"").hex()]


def test_hash_pairs_are_not_broadcast(spark):
    rows = spark.range(40).select(F.col("id").alias("image_id"), (F.col("id") * 3).alias("hi"), F.col("id").alias("lo"))
    pairs = det.hash_pairs(rows, 2)
    plan = pairs._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "BroadcastExchange" not in plan
    want = {(a, b) for a in range(40) for b in range(a + 1, 40) if bin(3 * a ^ 3 * b).count("1") + bin(a ^ b).count("1") <= 2}
    assert {(r["a"], r["b"]) for r in pairs.collect()} == want


def test_correction_broadcasts_only_bitmaps(spark, data):
    """Detection, rounds of components and correction all sent tables as large as the collection through the driver."""
    bus, store = spark.sparkContext._jsc.sc().listenerBus(), spark._jsparkSession.sharedState().statusStore()

    def plans():
        bus.waitUntilEmpty(30_000)
        runs = store.executionsList()
        return {(x := runs.apply(i)).executionId(): x.physicalPlanDescription() for i in range(runs.size())}

    before = plans()
    rows = methods.QUERIES["fp_correction_documents"](spark, data).collect()
    made = [text for k, text in plans().items() if k not in before]
    keys = [k for text in made for k in re.findall(r"\(\d+\) BroadcastHashJoin.*\nLeft keys.*?: \[(.*)\]", text)]
    assert rows and sum("SortMergeJoin" in text for text in made) > 3
    assert all(k.startswith("hit_bucket#") for k in keys), keys


def test_warp_joins_no_pixels(spark, data):
    df = more_methods.QUERIES["warp"](spark, data)
    assert "Join" not in df._jdf.queryExecution().optimizedPlan().toString()
    rows = df.collect()
    assert len(rows) == spark.read.parquet(f"{data}/embeddings.parquet").count()
    assert all((r["bytes"] is None) == (r["image_id"] % 7 == 3) for r in rows)


def test_more_collisions_than_rounds(spark):
    """Sixty contents under one digest and length: all were compared with one first member a round."""
    rows = [(i, f"p{i:03d}", f"text {i % 60:02d}", "same") for i in range(130)]
    sets = det.exact_sets(spark.createDataFrame(rows, "image_id long, path string, content string, digest string")).collect()
    assert {(r["set_id"], r["image_id"]) for r in sets} == {(f"bytes:{i % 60}", i) for i in range(130)}


def test_region_hashes_in_batches_are_those_of_one_image():
    """Also where blurred values lie at the threshold, and for images of several shapes in one batch."""
    rng = np.random.default_rng(1)
    flat = [np.full((64, 64), v, np.uint8) for v in (0, 127, 128, 129)]
    steps = [np.kron(rng.integers(126, 131, (9, 9)), np.ones((9, 9))).astype(np.uint8), np.kron(rng.integers(0, 2, (6, 6)), np.full((70, 60), 255)).astype(np.uint8)]
    noise = [rng.integers(0, 256, s).astype(np.uint8) for s in ((64, 64), (17, 400), (1, 1))] + [images.render(rng.standard_normal(64), 64) for _ in range(20)]
    for options in ({}, {"segment_limit": 2}, {"min_segment": 20, "size": 120}):
        assert segments.segment_hashes_many(flat + steps + noise, batch=4, **options) == [segments.segment_hashes(r, **options) for r in flat + steps + noise]
    assert segments.segment_hashes_many([]) == []
    stack = np.stack(noise[3:])
    assert (arithmetic.box_resize_many(stack, 32, 9) == np.stack([arithmetic.box_resize(r, 32, 9) for r in stack])).all()


def test_images_are_signed_in_one_pass(spark, data):
    """Digest and hashes were two passes over the pixels and a join of them."""
    made = images.sign(more_methods._renders(spark, data, size=64))
    assert "Join" not in made._jdf.queryExecution().optimizedPlan().toString()
    rows = made.collect()
    assert len(rows) == 6 * spark.read.parquet(f"{data}/embeddings.parquet").count() and all(len(r["digest"]) == 64 and r["length"] in (4096, 3600) for r in rows)


def test_links_of_images_without_listing_pairs(spark):
    """Many images share a region: their pairs were all joined, by each region that they share."""
    rng = np.random.default_rng(4)
    common = [0, 7885078839350357357, -1]
    rows = [(i, [common[k] for k in range(3) if rng.random() < 0.4] + rng.integers(-(2**63), 2**63 - 1, int(rng.integers(0, 4))).tolist()) for i in range(150)] + [(150, [])]
    rows += [(151, [int(rng.integers(2**62)), 5]), (152, [4, 5, 5])]
    hashed = spark.createDataFrame(rows + [(153, None)], "image_id long, segments array<long>").repartition(3)
    want = {}
    for a, x in rows:
        for b, y in rows:
            if a < b:
                near = [min(bin((h ^ g) & (2**64 - 1)).count("1") for g in y) for h in set(x)] if y else []
                want[a, b] = [d for d in near if d <= 3]
    for cutoff in (1, 2):
        pairs = {(a, b): (len(d), sum(d)) for (a, b), d in want.items() if len(d) >= cutoff}
        for block in (40, 100, 2048):
            got = images.segment_matches(hashed, cutoff, 0.05, block).collect()
            assert {(r["a"], r["b"]): (r["matched"], r["distance"]) for r in got} == pairs and len(got) == len(pairs)
            up = list(range(154))
            for a, b in sorted(pairs) * 9:
                up[a] = up[b] = min(up[a], up[b])
            links = {(i, sum(i in p for p in pairs), up[i]) for i in range(154)}
            assert {(r["image_id"], r["links"], r["component"]) for r in images.segment_links(hashed, cutoff, 0.05, block).collect()} == links


def test_variants_under_another_quality_are_compared_without_broadcasts(spark, data):
    """Features, pairs and qualities were broadcast. The actions keep the first quality, the variants have the second."""
    from pyspark.sql import functions as F

    from twinfold.operators import biometrics as bio
    from twinfold.queries import methods

    signed = methods._planted(spark, data)
    quality = signed.select("image_id", F.lit(2.5).alias("q")).where("image_id % 3 <> 0")
    columns = ("variant", "image_id", "path", "subject", "ahi", "vec")
    plain, other = methods._variants(signed), methods._variants(signed, quality=quality)
    key = lambda r: str(r)
    assert sorted(plain.select(*columns).collect(), key=key) == sorted(other.select(*columns).collect(), key=key)
    assert all(r["q"] == (2.5 if r["image_id"] % 3 else None) for r in other.collect())
    pairs = signed.select(F.col("image_id").alias("a"), (F.col("image_id") + 1).alias("b"))
    for df in (other, bio.compare(pairs, signed)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "Broadcast" not in plan
