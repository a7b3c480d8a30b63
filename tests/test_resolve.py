"""Hand-made cases of the rules: pairs per subject, merging, thresholds, missing values, counts, curves."""

import pytest
from pyspark.sql import functions as F

from twinfold.operators import baselines, biometrics as bio, detect as det, resolve as res, stats
from twinfold.plans.components import connected

SIGNED = "dataset string, image_id long, path string, subject string, content string, length long, digest string, hi long, lo long, ahi long, alo long, seg string, aseg string, vec array<long>, q double"


def signed(spark, rows):
    """rows: (id, subject, content, hash, vec, q)"""
    return spark.createDataFrame([("t", i, f"{s}/{i:04d}", s, c, len(c), c, h, 0, h, 0, f"r{h}", f"r{h}", v, q) for i, s, c, h, v, q in rows], SIGNED)


@pytest.mark.parametrize("n,circular,every", [(1, 0, 0), (2, 1, 1), (3, 3, 3), (6, 6, 15)])
def test_pairs_of_a_subject(spark, n, circular, every):
    c = spark.createDataFrame([("s", i, f"{i:03d}") for i in range(n)], "subject string, image_id long, path string")
    assert bio.mated_circular(c).count() == circular and bio.mated_all(c).count() == every
    assert sorted(map(tuple, bio.mated_circular(c, "index").collect())) == sorted(map(tuple, bio.mated_circular(c).collect()))
    row = bio.mated_counts(c).first()
    assert (row["circular"], row["all_pairs"]) == (circular, every)


def test_overlapping_sets_merge(spark):
    s = spark.createDataFrame([("a", 1), ("a", 2), ("b", 2), ("b", 3), ("c", 4), ("c", 5)], "set_id string, image_id long")
    want = [(1, 1), (1, 2), (1, 3), (4, 4), (4, 5)]
    assert sorted(map(tuple, res.merge(s).collect())) == want and sorted(map(tuple, res.merge_local(s).collect())) == want


def test_long_chain_and_star(spark):
    chain = [(i, i + 1) for i in range(64)] + [(1000, 1001 + i) for i in range(50)] + [(7, 7), (3, 2)]
    got = connected(spark.createDataFrame(chain, "u long, v long")).collect()
    assert len(got) == 65 + 51 and {r["component"] for r in got} == {0, 1000} and len({r["node"] for r in got}) == len(got)
    assert connected(spark.createDataFrame([], "u long, v long")).count() == 0


def test_weak_digest_is_separated(spark):
    c = spark.createDataFrame([(i, f"p{i}", t) for i, t in enumerate(["a", "b", "a", "c", "b", "a"])], "image_id long, path string, content string").withColumn("digest", F.lit("same"))
    got = {}
    for r in det.exact_sets(c).collect():
        got.setdefault(r["set_id"], set()).add(r["image_id"])
    assert sorted(map(sorted, got.values())) == [[0, 2, 5], [1, 4]]


@pytest.mark.parametrize("rule,left", [("strict", set()), ("lenient", {1, 2}), ("split", {1, 2}), ("none", {1, 2, 3})])
def test_correction_rules(spark, rule, left):
    comps = spark.createDataFrame([(1, 1), (1, 2), (1, 3)], "component long, image_id long")
    f = spark.createDataFrame([(1, [10, 0]), (2, [10, 1]), (3, [0, 10])], "image_id long, vec array<long>")
    assert {r["image_id"] for r in res.correct(comps, f, rule=rule).collect()} == left


def test_threshold_equality_passes_and_missing_features_stay(spark):
    comps = spark.createDataFrame([(1, 1), (1, 2), (5, 5), (5, 6)], "component long, image_id long")
    f = spark.createDataFrame([(1, [1, 0]), (2, [2, 1]), (5, [1, 0])], "image_id long, vec array<long>")
    score = res.pair_scores(comps, f).where("component = 1").first()["score"]
    tau = score / (1 << 20)
    assert res.correct(comps, f, tau=tau).count() == 4
    assert res.correct(comps, f, tau=tau + 2 / (1 << 20)).count() == 2
    assert res.correct(comps, f, tau=0.1, missing="expel").count() == 2
    assert res.correct(comps, f, tau=-1.0).count() == 4 and res.correct(comps, f, tau=1.1).count() == 2


def test_quality_order_with_nan_missing_and_ties(spark):
    nan = float("nan")
    rows = [(1, "s", "a", 1, None, nan), (2, "s", "b", 1, None, 3.0), (3, "s", "c", 1, None, 3.0), (4, "s", "d", 2, None, None), (5, "s", "e", 2, None, nan)]
    s = signed(spark, rows)
    comps = spark.createDataFrame([(1, 1), (1, 2), (1, 3), (4, 4), (4, 5)], "component long, image_id long")
    assert sorted(map(tuple, res.keep_best(comps, s).collect())) == [(1, 2), (4, 4)]


def test_six_poor_pairs_lose_nine_images(spark):
    """Three pairs within subjects lose one each; three across subjects resemble nobody and lose both."""
    rows = [(2 * i + k, f"a{i}", f"in{i}", 100 + i, [1, 0, 0], 1.0) for i in range(3) for k in (0, 1)]
    rows += [(20 + 2 * i + k, f"b{2 * i + k}", f"out{i}", 200 + i, [0, 1, 0], 1.0) for i in range(3) for k in (0, 1)]
    rows += [(40 + i, f"b{i}", f"ref{i}", 300 + i, [0, 0, 1], 1.0) for i in range(6)]
    s = signed(spark, rows)
    t1 = stats.overview(s, det.detect(s)).first()
    assert (t1["intra"], t1["subjects_with_intra"], t1["inter"], t1["subjects_with_inter"], t1["combined"]) == (6, 3, 6, 6, 12)
    t2 = stats.results(res.actions(s)).first()
    assert (t2["removed"], t2["moved"]) == (9, 0)


def test_margin_and_floor(spark):
    kept = spark.createDataFrame([(1, 10), (2, 20), (3, 30), (4, 40)], "component long, kept long")
    unit = float(1 << 20)
    f, m = res.fixed(0.40), res.fixed(0.20)
    scores = spark.createDataFrame([(1, 10, "x", float(f + m), 1), (1, 10, "y", float(f), 1), (2, 20, "x", float(f + m - 1), 1), (2, 20, "y", float(f), 1), (3, 30, "x", float(f), 1), (4, 40, "x", f - 1.0, 1)], "component long, kept long, subject string, mean double, n long")
    feats = spark.createDataFrame([(i, [1]) for i in (10, 20, 30, 40)], "image_id long, vec array<long>")
    got = {r["component"]: (r["target"], r["reason"]) for r in res.choose(kept, scores, feats).collect()}
    assert unit and got == {1: ("x", "assigned"), 2: (None, "thin_margin"), 3: ("x", "assigned"), 4: (None, "below_floor")}


def test_rates_eer_and_curve_by_hand(spark):
    rows = [(s, True, q) for s, q in zip([2, 4, 5, 6, 8], [1.0, 1.0, 2.0, 3.0, 4.0])] + [(s, False, 1.0) for s in [1, 2, 3, 5, 7]]
    sc = spark.createDataFrame(rows, "score long, mated boolean, pair_q double")
    curve = {r["threshold"]: (r["fnmr"], r["fmr"]) for r in bio.rates(sc).collect()}
    assert curve[5] == (0.4, 0.4) and curve[8] == (0.8, 0.0) and curve[1] == (0.0, 1.0)
    assert bio.eer(bio.rates(sc)).first()["eer"] == 0.4
    assert bio.fnmr_at(bio.rates(sc), [0.2]).first()["fnmr"] == 0.6
    fnmr = [v[0] for _, v in sorted(curve.items())]
    fmr = [v[1] for _, v in sorted(curve.items())]
    assert fnmr == sorted(fnmr) and fmr == sorted(fmr, reverse=True)
    edc = sorted((r["fraction"], r["error"]) for r in bio.edc(sc, "fnmr", 0.4).collect())
    assert edc[0] == (0.0, 0.4) and edc[1] == (0.4, 0.0)  # both misses had the lowest quality and go together
    assert bio.pauc(bio.edc(sc, "fnmr", 0.4)).first()["pauc"] == 0.08


def test_nonmated_falls_back_on_tiny_collections(spark):
    c = spark.createDataFrame([(i, f"p{i}", "one" if i < 3 else "two") for i in range(5)], "image_id long, path string, subject string")
    assert bio.nonmated(c, 6).count() == 6
    assert bio.nonmated(c.where("subject = 'one'"), 3).count() == 0


def test_nonmated_gives_as_many_as_asked_at_any_size(spark):
    """One image of one subject against three thousand of another: all 3000 pairs are asked for and come; and of a very uneven collection as many as there are mated ones."""
    c = spark.range(3001).select(F.col("id").alias("image_id"), F.format_string("p%05d", "id").alias("path"), F.when(F.col("id") == 1234, "one").otherwise("two").alias("subject"))
    got = bio.nonmated(c, 3000).collect()
    assert len(got) == len(set(map(tuple, got))) == 3000 and all((r["a"] == 1234) != (r["b"] == 1234) for r in got)
    uneven = c.withColumn("subject", F.when(F.col("image_id") % 50 == 0, F.concat(F.lit("s"), F.col("image_id").cast("string"))).otherwise("two"))
    some = bio.nonmated(uneven, 3000)
    own = {r["image_id"]: r["subject"] for r in uneven.collect()}
    got = some.collect()
    assert len(got) == len(set(map(tuple, got))) == 3000 and all(own[r["a"]] != own[r["b"]] for r in got)
    assert sorted(map(tuple, got)) == sorted(map(tuple, bio.nonmated(uneven.repartition(7), 3000).collect()))


def test_variants_in_one_pass_equal_each_alone(spark, data):
    from twinfold.sources import planted

    from twinfold.plans.storage import materialise

    s = materialise(planted.signed(spark, data), "s")
    both = s.withColumn("variant", F.lit("x")).unionByName(s.where("image_id % 3 <> 0").withColumn("variant", F.lit("y")))
    together = bio.comparisons(both)
    for v, alone in (("x", s), ("y", s.where("image_id % 3 <> 0"))):
        one = sorted(map(tuple, bio.comparisons(alone).select("a", "b", "mated", "score").collect()))
        assert one == sorted(map(tuple, together.where(F.col("variant") == v).select("a", "b", "mated", "score").collect()))


def test_prefix_sums_over_partitions(spark):
    rows = [(g, i, i * 3 % 7 + 1) for g in "ab" for i in range(500)]
    got = bio.prefix_sums(spark.createDataFrame(rows, "g string, x long, n long").repartition(5), ("g",), "x", "n").collect()
    for r in got:
        assert r["before_n"] == sum(n for g, x, n in rows if g == r["g"] and x < r["x"]) and r["total_n"] == sum(n for g, _, n in rows if g == r["g"])


def test_sets_of_two_hashes_overlap_and_merge(spark, data):
    """A crop that the region hash alone finds meets, over a shared image, a near copy that the frequency hash finds."""
    from twinfold.plans.storage import materialise
    from twinfold.sources import planted

    sets = materialise(det.detect(materialise(planted.signed(spark, data), "s")), "sets")
    by = {}
    for r in sets.collect():
        by.setdefault((r["detector"], r["variant"]), {}).setdefault(r["set_id"], set()).add(r["image_id"])
    dct, seg = by["dct", "original"].values(), by["segment", "original"].values()
    base, near, crop = 6, 1000010, 1000011
    assert any({base, near} <= x and crop not in x for x in dct) and any({near, crop} <= x and base not in x for x in seg)
    merged = {r["image_id"]: r["component"] for r in res.merge(sets).collect()}
    assert merged[base] == merged[near] == merged[crop]
    only_region = {i for x in seg for i in x} - {i for d in ("digest", "dct") for v in ("original", "aligned") for x in by.get((d, v), {}).values() for i in x}
    assert only_region


def test_detection_checks_bytes(spark):
    """Two contents with one digest are two sets; without contents the check refuses."""
    rows = [(i, "s", c, 100 + i, [1], 1.0) for i, c in enumerate(["a", "a", "b", "b", "c"])]
    s = signed(spark, rows).withColumn("digest", F.lit("same"))
    got = {}
    for r in det.detect(s, ("digest",)).collect():
        got.setdefault(r["set_id"], set()).add(r["image_id"])
    assert sorted(map(sorted, got.values())) == [[0, 1], [2, 3]]
    assert det.detect(s, ("digest",), verify=False).count() == 5
    with pytest.raises(ValueError):
        det.detect(s.drop("content"), ("digest",))


def test_radius_sets_are_components(spark):
    rows = [(0, "s", "a", 0b0000, None, None), (1, "s", "b", 0b0011, None, None), (2, "s", "c", 0b1111, None, None), (3, "s", "d", 0xFFFF0000, None, None)]
    got = det.detect(signed(spark, rows), ("dct",), ("original",), radius=2).collect()
    assert sorted(r["image_id"] for r in got) == [0, 1, 2] and len({r["set_id"] for r in got}) == 1


def test_passages_of_any_length_anywhere(spark):
    docs = [(1, "x one two"), (2, "one two three four five"), (3, "start alpha beta gamma"), (4, "pretty short"), (5, "aa bb cc dd"), (6, "line\nbreak here now"), (7, None), (8, "")]
    items = [(10, "one two"), (11, "three four five"), (12, "alpha beta gam"), (13, "short"), (14, "a bb cc d"), (15, "two three four five"), (16, "break here"), (17, "ne two three four fiv"), (18, "nowhere to be found at all"), (19, None)]
    d, i = (spark.createDataFrame(x, "image_id long, content string") for x in (docs, items))
    want = sorted((a, b) for a, t in docs for b, u in items if t is not None and u is not None and u in t)
    assert sorted(map(tuple, det.passages(d, i).collect())) == want and len(want) >= 8
    with pytest.raises(ValueError):
        det.passages(d, i, max_short=1)


def test_keep_first_and_long_hash(spark):
    s = signed(spark, [(1, "b", "x", 1, None, None), (2, "a", "x", 1, None, None)])
    assert res.keep_first(det.detect(s, ("digest",)), s).first()["kept"] == 2


def test_preservative_keeps_more_than_full_removal_and_actions_are_stable(spark, data):
    from twinfold.plans.storage import materialise
    from twinfold.sources import planted

    s = materialise(planted.signed(spark, data), "s")
    acts = res.actions(s)
    one = sorted(map(tuple, acts.select("image_id", "action", "reason", "to_subject").collect()), key=str)
    two = sorted(map(tuple, res.actions(s.repartition(7, "q")).select("image_id", "action", "reason", "to_subject").collect()), key=str)
    assert one == two
    sets = det.detect(s)
    kept = {r["image_id"] for r in res.preservative(s, acts).select("image_id").collect()}
    full = {r["image_id"] for r in res.full_removal(s, sets).select("image_id").collect()}
    gone = {r["image_id"] for r in acts.where("action = 'remove'").collect()}
    assert full < kept and not kept & gone and len(kept) + len(gone) == s.count()
    reasons = {r["reason"] for r in acts.select("reason").distinct().collect()}
    assert {"exact_copy", "best_quality", "lower_quality", "assigned", "thin_margin", "below_floor", "no_candidate"} <= reasons
    assert acts.where("action = 'move' and to_subject = from_subject").count() == 0
    centroid = sorted(map(tuple, res.actions(s, strategy="centroid").select("image_id", "action", "reason", "to_subject").collect()), key=str)
    assert centroid == one


def test_label_propagation_finds_two_cliques(spark):
    edges = [(a, b, 10) for g in ((1, 2, 3, 4), (11, 12, 13)) for a in g for b in g if a < b] + [(4, 11, 1)]
    e = spark.createDataFrame(edges, "u long, v long, score long")
    got = {r["image_id"]: r["community"] for r in baselines.communities(e, "label_propagation", 3).collect()}
    assert len({got[i] for i in (1, 2, 3, 4)}) == 1 and len({got[i] for i in (11, 12, 13)}) == 1 and got[1] != got[11]


def test_band_planner_refuses():
    """More bands that must agree together are wider keys; the cheapest number is taken, and what no number makes cheap is refused."""
    one, two = det.plan_bands(100, 3), det.plan_bands(10**6, 3)
    assert (one["bands"], one["agree"], two["bands"], two["agree"]) == (4, 1, 5, 2) and two["candidates_per_image"] < 10**6 * 4 / 2**16
    with pytest.raises(ValueError):
        det.plan_bands(10**9, 6)


def test_bitmap_reducer_loses_nothing(spark):
    from twinfold.plans.bitmaps import drop_rows, reduce_by, split_by

    wide, keys = spark.range(5000).withColumnRenamed("id", "k"), spark.range(0, 5000, 37).withColumnRenamed("id", "k")
    got = {r["k"] for r in reduce_by(wide, keys, "k").collect()}
    assert {r["k"] for r in keys.collect()} <= got and len(got) < 1500
    hit, rest = split_by(wide, keys, "k")
    assert hit.count() + rest.count() == 5000
    assert drop_rows(wide, keys, "k").count() == 5000 - keys.count()
    assert reduce_by(wide, keys.where("false"), "k").count() == 0 and drop_rows(wide, keys.where("false"), "k").count() == 5000


def test_tiles_hold_every_pair_once(spark):
    comps = spark.createDataFrame([(1, i) for i in range(40)] + [(100, 100), (100, 101)], "component long, image_id long")
    f = spark.createDataFrame([(i, [i + 1, 3]) for i in [*range(40), 100, 101]], "image_id long, vec array<long>")
    one = sorted(map(tuple, res.pair_scores(comps, f).collect()))
    assert len(one) == 40 * 39 // 2 + 1 and one == sorted(map(tuple, res.pair_scores(comps, f, chunk=7).collect()))


def test_late_rows_are_dropped_behind_the_watermark(spark, tmp_path):
    from twinfold.streaming import filters as st

    def put(name, rows):
        spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / "in" / name))

    put("a", [(10 * 86400, "x"), (10 * 86400 + 5, "x"), (20 * 86400, "y")])
    src = lambda: st.stamped(st.arriving(spark, f"file://{tmp_path}/in/*", "doc_id long, text string"))
    mark = f"file://{tmp_path}/mark"
    one = st.drain(st.exact_filter(src(), "1 day").select("doc_id", "text"), checkpoint=mark)
    assert sorted(r["text"] for r in one.collect()) == ["x", "y"]
    put("b", [(86400, "late"), (21 * 86400, "z"), (20 * 86400 + 1, "y")])
    two = st.drain(st.exact_filter(src(), "1 day").select("doc_id", "text"), checkpoint=mark)
    assert sorted(r["text"] for r in two.collect()) == ["x", "y", "z"]  # late row dropped, copy within the watermark filtered, the checkpoint remembered


def test_kept_copy_changes_with_a_smaller_path(spark, tmp_path):
    from twinfold.streaming import filters as st

    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        mark = f"file://{tmp_path}/mark"
        src = lambda: st.arriving(spark, f"file://{tmp_path}/in/*", "text string, path string")
        spark.createDataFrame([("t", "m"), ("t", "k"), ("u", "a")], "text string, path string").coalesce(1).write.parquet(str(tmp_path / "in/a"))
        first = {tuple(r)[1:] for r in st.drain(st.keep_changes(src()), checkpoint=mark).collect()}
        assert first == {("k", "keep"), ("a", "keep")}
        spark.createDataFrame([("t", "b"), ("u", "z")], "text string, path string").coalesce(1).write.parquet(str(tmp_path / "in/b"))
        assert {tuple(r)[1:] for r in st.drain(st.keep_changes(src()), checkpoint=mark).collect()} == {("k", "keep"), ("a", "keep"), ("k", "unkeep"), ("b", "keep")}
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")


def test_persisted_store_is_idempotent(spark, tmp_path):
    from twinfold.streaming import filters as st

    spark.createDataFrame([(1, "x"), (2, "x"), (3, "y")], "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / "in/a"))
    src = lambda: st.arriving(spark, f"file://{tmp_path}/in/*", "doc_id long, text string")
    store = f"file://{tmp_path}/store"
    for mark in ("m1", "m2"):  # a fresh checkpoint reads everything again
        st.fill_store(src(), store, f"file://{tmp_path}/{mark}")
        got = spark.read.schema("digest string, doc_id long, batch long").parquet(store).collect()
        assert sorted(r["doc_id"] for r in got) == [1, 3]

def test_zero_features_are_no_evidence(spark, tmp_path):
    """The planner makes unit vectors before it drops zero ones; signed shingle counts of a short text may cancel out."""
    rows = [(1, "a", [3, 4]), (2, "a", [0, 0]), (3, "b", [4, -3]), (4, "b", None), (5, "c", [0, 0]), (6, "a", [6, 8]), (7, "b", [0, 0])]
    spark.createDataFrame(rows, "image_id long, subject string, vec array<long>").write.parquet(f"{tmp_path}/images")
    images = spark.read.parquet(f"{tmp_path}/images")
    kept = spark.createDataFrame([(1, 6), (2, 7)], "component long, kept long")
    involved = spark.createDataFrame([(1, "a"), (1, "b"), (1, "c"), (2, "a"), (2, "b")], "component long, subject string")
    references = images.where("image_id < 6")
    for strategy in ("centroid", "pairs"):
        got = res.subject_scores(kept, involved, references, images, strategy).collect()
        assert sorted((r["component"], r["kept"], r["subject"], round(r["mean"] / 2**20, 5), r["n"]) for r in got) == [(1, 6, "a", 1.0, 1), (1, 6, "b", 0.0, 1)]


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_actions_send_no_table_through_the_driver(spark, data):
    """Sets, members and kept images were broadcast, and the last plan held every step after the correction, some of them several times."""
    from twinfold.plans.storage import materialise
    from twinfold.sources import planted

    signed = materialise(planted.signed(spark, data), "signed")
    acts = res.actions(signed)
    plan = _plan(acts)
    assert "SortMergeJoin" in plan and "Broadcast" not in plan and plan.count("Exchange") <= 8
    acts = materialise(acts, "actions")
    for df in (res.preservative(signed, acts), res.full_removal(signed, acts), res.keep_best(acts.select("image_id", F.lit(1).alias("component")), signed)):
        assert "SortMergeJoin" in _plan(df) and "Broadcast" not in _plan(df)
