import numpy as np
import pytest

from twinfold.functions import arithmetic as ar
from twinfold.functions.blake3 import blake3
from twinfold.functions.segments import regions, segment_hashes
from twinfold.operators.preprocess import FIVE_POINT, warp_array
from twinfold.sources.images import edit, png, render

#: Published vectors: input byte i is i mod 251.
VECTORS = {
    0: "af1349b9f5f9a1a6a0404dea36dcc9499bcb25c9adc112b7cc9a93cae41f3262",
    1: "2d3adedff11b61f14c886e35afa036736dcd87a74d27b5c1510225d0f592e213",
    1024: "42214739f095a406f3fc83deb889744ac00df831c10daa55189b5d121c855af7",
    1025: "d00278ae47eb27b34faecf67b4fe263f82d5412916c1ffd97c8cb7fb814b8444",
    31744: "62b6960e1a44bcc1eb1a611a8d6235b6b4b78f32e7abc4fb4c6cdcce94895c47",
}


@pytest.mark.parametrize("n", VECTORS)
def test_blake3(n):
    assert blake3(bytes(i % 251 for i in range(n))).hex() == VECTORS[n]


def test_frequency_hash_invariances():
    r = np.random.default_rng(1).integers(0, 200, (3, 32, 32))
    bits = ar.dct_bits(r)
    assert (ar.dct_bits(r * 3) == bits).all()
    lighter = ar.dct_bits(r + 20)
    assert (lighter[:, 1:] != bits[:, 1:]).sum() <= 3  # only the constant term moves, and with it the median by one place
    assert (ar.dct_bits(r[:, :, ::-1]) != bits).any()


def test_flat_image_sets_at_most_the_constant_term():
    assert ar.dct_bits(np.full((1, 32, 32), 77)).sum() <= 1


def test_pack_order():
    bits = np.zeros((1, 64), bool)
    bits[0, 0] = bits[0, 63] = True
    assert ar.pack(bits).tolist() == [[1 << 31, 1]]


def test_regions_of_a_spiral():
    m = np.array([[1, 1, 1, 1], [0, 0, 0, 1], [1, 1, 0, 1], [1, 0, 0, 1], [1, 1, 1, 1]], bool)
    label = regions(m)
    assert len(set(label[m])) == 1 and (label[~m] == 0).all()


def test_regions_against_flood_fill():
    rng = np.random.default_rng(3)
    m = rng.random((40, 50)) < 0.55
    label, seen = regions(m), np.zeros(m.shape, bool)
    names = set()
    for y, x in zip(*np.nonzero(m)):
        if seen[y, x]:
            continue
        stack, own = [(y, x)], set()
        seen[y, x] = True
        while stack:
            a, b = stack.pop()
            own.add(label[a, b])
            for c, e in ((a + 1, b), (a - 1, b), (a, b + 1), (a, b - 1)):
                if 0 <= c < 40 and 0 <= e < 50 and m[c, e] and not seen[c, e]:
                    seen[c, e] = True
                    stack.append((c, e))
        assert len(own) == 1 and not own & names
        names |= own


def test_segment_hash_finds_the_frame_when_there_is_no_region():
    assert len(segment_hashes(np.full((64, 64), 10, np.uint8))) == 1
    checker = (np.indices((300, 300)).sum(0) % 2 * 255).astype(np.uint8)
    assert segment_hashes(checker, min_segment=10**6) == segment_hashes(checker, min_segment=10**6)


def test_frequency_hash_is_robust_on_renders_and_segment_hash_less_so():
    rng = np.random.default_rng(5)
    same = {"brighter": 0, "noise": 0}
    for _ in range(20):
        x = render(rng.standard_normal(64), 64)
        h = ar.dct_bits(ar.box_resize(x, 32, 32)[None])
        for how in same:
            y = edit(x, how, 1)
            same[how] += (ar.dct_bits(ar.box_resize(y, 32, 32)[None]) != h).sum() <= 6
    assert same["brighter"] >= 18 and same["noise"] >= 18


def test_identity_warp_and_png():
    x = render(np.random.default_rng(2).standard_normal(64), 112)
    assert (warp_array(x, 1.0, 0.0, 0.0, 0.0) == x).all()
    assert png(x).startswith(b"\x89PNG")


def test_similarity_transform_recovers_a_known_matrix(spark):
    from pyspark.sql import functions as F

    from twinfold.operators.preprocess import similarity_transform

    c, s = 2 * np.cos(np.pi / 6), 2 * np.sin(np.pi / 6)
    points = [(float(c * x - s * y + 11), float(s * x + c * y - 7)) for x, y in FIVE_POINT]
    df = spark.createDataFrame([(points,)], "p array<struct<x:double,y:double>>").select(similarity_transform(F.col("p")).alias("m"))
    m = df.first()["m"]
    for (x, y), (u, v) in zip(points, FIVE_POINT):
        assert abs(m["a"] * x - m["b"] * y + m["tx"] - u) < 1e-9 and abs(m["b"] * x + m["a"] * y + m["ty"] - v) < 1e-9


def test_image_directories(spark, tmp_path):
    from twinfold.sources.images import binary_dir, decoded_dir

    x = render(np.random.default_rng(2).standard_normal(64), 32)
    for i in range(3):
        (tmp_path / f"{i}.png").write_bytes(png(x))
    assert binary_dir(spark, str(tmp_path), "*.png").count() == 3
    rows = decoded_dir(spark, str(tmp_path)).collect()
    assert len(rows) == 3 and bytes(rows[0]["pixels"]) == x.tobytes()


def test_sql_names(spark):
    from twinfold.functions.registry import register

    register(spark)
    row = spark.sql("select hamming64(7L, 1L) as h, cosine_fx(array(1L, 0L), array(1L, 1L)) as c, normalise_tokens('A b, C!') as n, blake3(cast('' as binary)) as d, dct_hash('a b c') as x").first()
    assert (row["h"], row["c"], row["n"], row["d"]) == (2, 741455, "a b c", VECTORS[0]) and len(row["x"]) == 2


def test_run_reports(spark):
    import json

    from pyspark.sql import functions as F

    from twinfold.plans import report

    df = spark.range(100).select((F.col("id") % 7).alias("k"), "id")
    assert tuple(report.skew(df, "k").first()) == (100, 7, 15, 0.15)
    assert {r["k"]: r["total"] for r in report.salted_sum(df, "k", "id", 4).collect()} == {k: sum(range(k, 100, 7)) for k in range(7)}
    rows, obs = report.observed(df, "seen", n=F.count(F.lit(1)))
    rows.write.format("noop").mode("overwrite").save()
    assert obs.get == {"n": 100} and json.loads(report.manifest(spark, tau=0.4))["parameters"] == {"tau": 0.4}


def test_scan_binary_reads_every_file(spark, data):
    import os

    from twinfold.queries import more_methods

    want = sorted((f, os.path.getsize(os.path.join(at, f))) for at, _, names in os.walk(data) for f in names if not f.startswith((".", "_")))
    assert sorted((r["file"], r["length"]) for r in more_methods.scan_binary(spark, data).select("file", "length").collect()) == want and len(want) > 1


def test_renders_are_hashed_as_in_numpy_and_matched_as_by_brute_force(spark, data):
    """Both image hashes of renders and edits, and region matches at the default settings, by tiles of several sizes and, at a strict setting, by bands."""
    from twinfold.plans.storage import materialise
    from twinfold.sources import images

    e = spark.read.parquet(f"{data}/embeddings.parquet").where("vec_id < 40")
    edits = ("identity", "noise", "crop")
    hashed = materialise(images.hashes(images.rendered(e, edits, 64)), "hashed")
    got = {r["image_id"]: r for r in hashed.collect()}
    want = {}
    for r in e.collect():
        base = render(r["embedding"], 64)
        for k, how in enumerate(edits):
            x = edit(base, how, r["vec_id"])
            want[10 * r["vec_id"] + k] = ar.pack(ar.dct_bits(ar.box_resize(x, 32, 32)[None]))[0].tolist(), segment_hashes(x)
    assert {i: ([r["hi"], r["lo"]], list(r["segments"])) for i, r in got.items()} == want

    def brute(cutoff, limit):
        out = set()
        for a in want:
            for b in want:
                if a < b:
                    left, right = (np.array(sorted(set(want[i][1])), np.int64).view(np.uint64) for i in (a, b))
                    d = np.bitwise_count(left[:, None] ^ right[None, :]).min(axis=1)
                    if (d <= limit).sum() >= cutoff:
                        out.add((a, b, int((d <= limit).sum()), int(d[d <= limit].sum())))
        return out

    for block in (4096, 37):
        assert set(map(tuple, images.segment_matches(hashed, block=block).collect())) == brute(1, 16)
    assert set(map(tuple, images.segment_matches(hashed, 2, 0.05).collect())) == brute(2, 3)


def test_render_hashes_gives_every_region_hash(spark, data):
    """Its rows held the number of the region hashes, not the hashes."""
    from twinfold.queries import more_methods
    from twinfold.sources.images import EDITS

    rows = {r["image_id"]: r for r in more_methods.render_hashes(spark, data).collect()}
    vectors = spark.read.parquet(f"{data}/embeddings.parquet").orderBy("vec_id").limit(4).collect()
    for r in vectors:
        for k, how in enumerate(EDITS):
            x = edit(render(r["embedding"], 64), how, r["vec_id"])
            got = rows[10 * r["vec_id"] + k]
            assert list(got["segments"]) == segment_hashes(x) and got["regions"] == len(got["segments"])
            assert [got["hi"], got["lo"]] == ar.pack(ar.dct_bits(ar.box_resize(x, 32, 32)[None]))[0].tolist()


def test_images_are_scaled_smoothly_before_regions_are_sought():
    """Small images were blown up by repeating pixels: a ramp became stairs. A flat image stays flat, also at the threshold."""
    from twinfold.functions import segments

    for n in (20, 64, 300, 700):
        ramp = np.tile(np.linspace(0, 255, n), (n, 1))
        line = segments._blurred(ramp, 300)[150]
        want = np.interp((np.arange(300) + 0.5) * n / 300 - 0.5, np.arange(n), ramp[0])
        inner = slice(60, 240)
        assert np.abs(line - want)[inner].max() < 0.5 and np.diff(line)[inner].min() > 0.5
        plain = np.full((n, n), 128, np.uint8)
        assert segment_hashes(plain) == segment_hashes(plain, min_segment=300 * 300 - 1) == [0] == segments.segment_hashes_many([plain])[0]


def test_long_and_gradient_hashes_against_plain_versions(spark):
    import hashlib

    from twinfold.sources import catalog

    texts = ["one two three two", "", "Word " * 300 + "other", "a b c d e f g h 1 2 3"]
    corpus = spark.createDataFrame(list(enumerate(texts)), "image_id long, content string")
    long_ = {r["image_id"]: list(r["words"]) for r in catalog.long_hash(corpus).collect()}
    grad = {r["image_id"]: (r["hi"], r["lo"]) for r in catalog.gradient_hash(corpus).collect()}
    for i, t in enumerate(texts):
        digits = [int(hashlib.md5(w.encode()).hexdigest()[:3], 16) for w in t.lower().split()]
        count = np.zeros(1024, int)
        for d in digits:
            count[d % 1024] += 1
        assert long_[i] == ar.pack(ar.dct_bits(ar.luminance(count).reshape(1, 32, 32), 16))[0].tolist()
        cells = [[sum(d % 72 == 9 * r + c for d in digits) for c in range(9)] for r in range(8)]
        bits = "".join("1" if cells[r][c + 1] > cells[r][c] else "0" for r in range(8) for c in range(8))
        assert grad[i] == (int(bits[:32], 2), int(bits[32:], 2))


def test_region_hash_of_text_ignores_short_lines_and_case(spark):
    from twinfold.sources import catalog

    rows = [(0, "One two three four five\nshort line\nsix seven eight nine ten"), (1, "one TWO three, four five\n\nsix seven eight nine ten"), (2, "six seven eight nine ten\none two three four five"), (3, "a b"), (4, "a b")]
    c = spark.createDataFrame([("d", i, str(i), "s", t) for i, t in rows], "dataset string, image_id long, path string, subject string, content string")
    got = {r["image_id"]: r for r in catalog.sign(c, ("segment",)).collect()}
    assert got[0]["seg"] == got[1]["seg"] != got[2]["seg"] and got[3]["seg"] == got[4]["seg"] and got[3]["aseg"] is None and got[0]["hi"] is None and got[0]["vec"] is None
    with pytest.raises(ValueError):
        catalog.sign(c, ("nothing",))
