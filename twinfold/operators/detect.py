"""Exact and near duplicate sets in long form: ``set_id, image_id, detector, variant``."""

from __future__ import annotations

import math
from functools import reduce
from itertools import combinations

import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F
from pyspark.sql.types import StringType

from ..functions import arithmetic
from ..functions.blake3 import hex_digests
from ..plans.bitmaps import reduce_by
from ..plans.components import connected
from ..plans.shipping import ship
from ..plans.storage import materialise

DETECTORS = ("digest", "dct", "segment")


def with_digest(corpus: DataFrame, algo: str = "sha2", bits: int | None = None) -> DataFrame:
    """``digest`` beside each row. The JVM's digests are the fast way; ``blake3`` runs in Arrow batches; ``bits`` weakens a checksum on purpose."""
    raw = F.col("content").cast("binary")
    if algo == "blake3":
        ship(corpus.sparkSession)

        @F.pandas_udf(StringType())
        def digest(content: pd.Series) -> pd.Series:
            return pd.Series(hex_digests(content.tolist()), dtype=object)

        return corpus.withColumn("digest", digest(raw))
    made: Column = {"sha2": F.sha2(raw, 256), "md5": F.md5(raw), "crc32": F.crc32(raw), "xxhash64": F.xxhash64(raw)}[algo]
    if bits:
        made = made.bitwiseAND(F.lit((1 << bits) - 1))
    return corpus.withColumn("digest", made.cast("string"))


def repeated(rows: DataFrame, *keys: str) -> DataFrame:
    """Rows whose key occurs at least twice. Counting is partial per task, so one key with very many rows is no task of its own; the join back is split where it is skewed.
    A sorted merge by hint, as in all joins here whose sides grow with the collection: their compressed sizes look small, and the planner would send them through the driver.
    """
    many = rows.groupBy(*keys).agg(F.count("*").alias("_n")).where("_n > 1").select(*keys)
    return rows.join(many.hint("merge"), list(keys), "left_semi")


def exact_candidates(digested: DataFrame) -> DataFrame:
    """Images that share digest and length with another: all true copies, and possibly a collision. Content, where it is all there is, is read once for its length."""
    length = F.col("length") if "length" in digested.columns else F.octet_length("content")
    narrow = digested.select("image_id", "path", "digest", length.alias("length"))
    return repeated(materialise(narrow, "signatures"), "digest", "length")


def exact_classes(candidates: DataFrame, contents: DataFrame, max_rounds: int = 20) -> DataFrame:
    """``image_id, digest, rep, round``: candidates split by their bytes. Round 0 compares each digest's members with its first one; with an honest digest nothing is left. What is left of a collision is grouped
    by its bytes in round 1, whatever the number of classes, so that ``max_rounds`` of one round is the only one that can be too few.

    Only candidates' bytes are read again (a bounded bitmap keeps the rest of ``contents(image_id, content)`` out of the join) and written once; rounds write ids.
    """
    narrow = materialise(candidates.select("image_id", "path", "digest"), "candidates")
    read = reduce_by(contents.select("image_id", "content"), narrow, "image_id")
    whole = materialise(narrow.hint("merge").join(read, "image_id"), "verify")
    first = whole.groupBy("digest").agg(F.min(F.struct("path", "image_id", "content")).alias("r"))
    same = F.col("content") == F.col("r.content")
    judged = materialise(whole.join(first.hint("merge"), "digest").select("image_id", "digest", F.col("r.image_id").alias("rep"), same.alias("same")), "judged")
    done = judged.where("same").select("image_id", "digest", "rep", F.lit(0).alias("round"))
    rest = judged.where("not same").select("image_id")
    if rest.isEmpty():
        return done
    if max_rounds < 2:
        raise RuntimeError(f"{max_rounds} rounds did not separate the collisions; use a wider digest")
    left = whole.join(rest.hint("merge"), "image_id", "left_semi")
    classes = materialise(left.groupBy("digest", "content").agg(F.min(F.struct("path", "image_id")).alias("r")), "classes")
    more = left.join(classes.hint("merge"), ["digest", "content"]).select("image_id", "digest", F.col("r.image_id").alias("rep"), F.lit(1).alias("round"))
    return done.unionByName(materialise(more, "judged"))


def exact_sets(digested: DataFrame, max_rounds: int = 20) -> DataFrame:
    """Sets of byte-equal images, named by their first member; ``digested`` has ``content`` and ``digest``."""
    classes = exact_classes(exact_candidates(digested), digested, max_rounds)
    return repeated(classes, "rep").select(F.concat(F.lit("bytes:"), F.col("rep").cast("string")).alias("set_id"), "image_id", F.lit("digest").alias("detector"), F.lit("original").alias("variant"))


def by_content(corpus: DataFrame) -> DataFrame:
    """The plain alternative: group on the bytes themselves, which shuffles all of them."""
    return repeated(corpus.select("image_id", "content"), "content").select("image_id", F.md5(F.col("content").cast("binary")).alias("set_id"))


def digest_sets(signed: DataFrame, contents: DataFrame | None = None) -> DataFrame:
    """Exact sets named by their digest. With ``contents`` the bytes decide: a collision's further classes get names of their own. Without, equal digests do."""
    rows = signed.select("image_id", "path", "digest", "length") if contents is not None else signed.select("image_id", "digest")
    name = F.concat(F.lit("digest:"), "digest")
    if contents is not None:
        rows = repeated(exact_classes(exact_candidates(rows), contents), "rep")
        name = F.when(F.col("round") == 0, name).otherwise(F.concat(name, F.lit(":"), F.col("rep").cast("string")))
    else:
        rows = repeated(rows, "digest")
    return rows.select(name.alias("set_id"), "image_id", F.lit("digest").alias("detector"), F.lit("original").alias("variant"))


def hash_sets(signed: DataFrame, variant: str = "original", radius: int = 0) -> DataFrame:
    """Images of equal frequency hash; with ``radius``, components of hashes within so many bits. Failed alignments (null hashes) take no part in the aligned pass."""
    hi, lo = ("ahi", "alo") if variant == "aligned" else ("hi", "lo")
    rows = signed.where(F.col(hi).isNotNull()).select("image_id", F.col(hi).alias("hi"), F.col(lo).alias("lo"))
    tail = ("image_id", F.lit("dct").alias("detector"), F.lit(variant).alias("variant"))
    if radius:
        rows = materialise(rows, "hashes")
        reps = rows.groupBy("hi", "lo").agg(F.min("image_id").alias("rep"))
        edges = rows.join(reps, ["hi", "lo"]).select(F.col("image_id").alias("u"), F.col("rep").alias("v")).unionByName(hash_pairs(rows, radius).select(F.col("a").alias("u"), F.col("b").alias("v")))
        return connected(edges).select(F.concat_ws(":", F.lit(f"dct{radius}"), F.lit(variant), F.col("component").cast("string")).alias("set_id"), F.col("node").alias("image_id"), *tail[1:])
    name = F.concat_ws(":", F.lit("dct"), F.lit(variant), F.col("hi").cast("string"), F.col("lo").cast("string"))
    return repeated(rows, "hi", "lo").select(name.alias("set_id"), *tail)


def segment_sets(signed: DataFrame, variant: str = "original") -> DataFrame:
    """Images whose whole lists of region hashes are equal."""
    c = "aseg" if variant == "aligned" else "seg"
    rows = signed.where(F.col(c).isNotNull()).select("image_id", F.col(c).alias("seg"))
    return repeated(rows, "seg").select(F.concat_ws(":", F.lit("segment"), F.lit(variant), "seg").alias("set_id"), "image_id", F.lit("segment").alias("detector"), F.lit(variant).alias("variant"))


def bands(hi: Column, lo: Column, n: int) -> Column:
    """The 64 bits cut to ``n`` bands: array of (band, value)."""
    out, at = [], 0
    for b in range(n):
        width = (64 - at) // (n - b)
        value = F.lit(0).cast("long")
        for half, base in ((hi, 0), (lo, 32)):
            lo_bit, hi_bit = max(at, base), min(at + width, base + 32)
            if lo_bit < hi_bit:
                k = hi_bit - lo_bit
                part = F.shiftrightunsigned(half, 32 - (hi_bit - base)).bitwiseAND(F.lit((1 << k) - 1))
                value = F.shiftleft(value, k).bitwiseOR(part)
        out.append(F.struct(F.lit(b).alias("band"), value.alias("value")))
        at += width
    return F.array(*out)


def hash_pairs(signed: DataFrame, radius: int = 6, budget: float = 1e5) -> DataFrame:
    """All pairs of different hashes within ``radius`` bits, and the images of equal hash through their class: ``a, b, distance`` between class representatives.

    Equal hashes are one class first, so a flat image's giant class costs one row. Of radius + g bands at least g agree (pigeonhole), so a join on every choice of g bands loses nothing; more bands at once are wider
    keys with fewer candidates and more rows. ``plan_bands`` takes the g that costs least, and refuses beyond the budget of candidates an image.
    """
    rows = materialise(signed.groupBy("hi", "lo").agg(F.min("image_id").alias("rep")), "hashes")
    plan = plan_bands(rows.count(), radius, budget)
    cut = bands(F.col("hi"), F.col("lo"), plan["bands"])
    choices = [F.struct(F.lit(j).alias("choice"), F.array(*[cut[i]["value"] for i in own]).alias("key")) for j, own in enumerate(combinations(range(plan["bands"]), plan["agree"]))]
    keyed = rows.select("rep", "hi", "lo", F.explode(F.array(*choices)).alias("k")).select("rep", "hi", "lo", "k.choice", F.xxhash64("k.choice", "k.key").alias("key"))
    a, b = keyed.alias("a"), keyed.alias("b")
    d = arithmetic.hamming(F.col("a.hi"), F.col("a.lo"), F.col("b.hi"), F.col("b.lo"))
    # sorted merge: the planner does not see how many keys a hash has and would send them all through the driver
    near = a.join(b.hint("merge"), (F.col("a.key") == F.col("b.key")) & (F.col("a.choice") == F.col("b.choice")) & (F.col("a.rep") < F.col("b.rep"))).where(d <= radius)
    return near.select(F.col("a.rep").alias("a"), F.col("b.rep").alias("b"), d.alias("distance")).distinct()


def hash_histogram(signed: DataFrame) -> DataFrame:
    """How many hashes have how many images: shows degenerate (flat) images before anything is paired."""
    return signed.groupBy("hi", "lo").agg(F.count("*").alias("images")).groupBy("images").agg(F.count("*").alias("hashes"))


def plan_bands(images: int, radius: int, budget: float = 1e3) -> dict[str, float]:
    """``bands`` of the 64 bits, how many must ``agree``, and the expected candidates an image: the cheapest of one to three agreeing bands (a key row costs about as much as a candidate). Refuses beyond the budget."""
    plans = []
    for agree in (1, 2, 3):
        n = radius + agree
        if n <= 32:
            keys, width = math.comb(n, agree), agree * (64 // n)
            plans.append((keys + keys * images / 2**width, n, agree, keys * images / 2**width))
    _, n, agree, per_image = min(plans)
    if per_image > budget:
        raise ValueError(f"radius {radius} over {images} images gives about {per_image:.0f} candidates an image; use a smaller radius or a longer hash")
    return {"bands": n, "agree": agree, "candidates_per_image": per_image}


def detect(signed: DataFrame, detectors=DETECTORS, variants=("original", "aligned"), within_subject_only: bool = False, verify: bool = True, contents: DataFrame | None = None, radius: int = 0) -> DataFrame:
    """All families of sets, unmerged: byte copies, equal frequency hashes and equal region hashes, the latter two on originals and on aligned crops.

    ``verify`` compares the bytes of images with equal digests; they come from ``contents(image_id, content)`` or from ``signed`` itself. ``radius`` widens the frequency hash.
    ``within_subject_only`` looks at each subject alone, as filters of single collections do.
    """
    if unknown := set(detectors) - set(DETECTORS):
        raise ValueError(f"unknown detectors {sorted(unknown)}")
    if contents is None and "content" in signed.columns:
        contents = signed
    parts = []
    if "digest" in detectors:
        if verify and contents is None:
            raise ValueError("the byte check needs contents (or verify=False)")
        parts.append(digest_sets(signed, contents if verify else None))
    if "dct" in detectors:
        parts += [hash_sets(signed, v, radius) for v in variants]
    if "segment" in detectors:
        parts += [segment_sets(signed, v) for v in variants]
    if not parts:
        return signed.select(F.lit("").alias("set_id"), "image_id", F.lit("").alias("detector"), F.lit("").alias("variant")).where("false")
    out = reduce(DataFrame.unionByName, parts)
    if within_subject_only:
        own = out.join(signed.select("image_id", "subject"), "image_id").withColumn("set_id", F.concat_ws("|", "set_id", "subject")).drop("subject")
        out = repeated(own, "set_id").select("set_id", "image_id", "detector", "variant")
    return out


def between(signed: DataFrame, variant: str = "original") -> DataFrame:
    """Sets that span several datasets; ids are local to a dataset, so a member is (dataset, image_id)."""
    hi, lo = ("hi", "lo") if variant == "original" else ("ahi", "alo")
    rows = signed.where(F.col(hi).isNotNull()).select("dataset", "image_id", F.col(hi).alias("hi"), F.col(lo).alias("lo"))
    wide = rows.groupBy("hi", "lo").agg(F.count_distinct("dataset").alias("n")).where("n > 1")
    return rows.join(wide.select("hi", "lo"), ["hi", "lo"], "left_semi").select(F.concat_ws(":", F.lit(variant), F.col("hi").cast("string"), F.col("lo").cast("string")).alias("set_id"), "dataset", "image_id")


def passages(docs: DataFrame, items: DataFrame, max_short: int = 10_000) -> DataFrame:
    """``image_id, item_id``: documents whose ``content`` contains an item's ``content``, compared in full.

    Words inside an item (all but its first and last) are whole words of any text that contains it, so the first three of them (two or one, where there are no more) are a join key that every such text has at
    one of its positions. Items without an inner word have no key: they are few and short, and are compared with all texts by broadcast after a check of their number.
    """
    words = F.split(F.trim(F.regexp_replace("content", r"\s+", " ")), " ")
    sized = materialise(items.where("content is not null").select(F.col("image_id").alias("item_id"), F.col("content").alias("item"), F.least(F.size(words) - 2, F.lit(3)).alias("k"), words.alias("w")), "items")
    text = docs.where("content is not null").select("image_id", "content")
    parts = []
    for k in sorted(r["k"] for r in sized.select("k").distinct().collect()):  # at most five values
        some = sized.where(F.col("k") == k)
        if k < 1:
            if some.limit(max_short + 1).count() > max_short:
                raise ValueError(f"more than {max_short} items of at most two words")
            parts.append(text.join(F.broadcast(some.select("item_id", "item")), F.contains("content", "item")).select("image_id", "item_id"))
            continue
        run = lambda i: F.xxhash64(F.array_join(F.slice("w", i, k), " "))  # noqa: B023, E731
        keys = some.select("item_id", run(F.lit(2)).alias("key"))
        at = F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), run)
        windows = text.select("image_id", words.alias("w")).where(F.size("w") >= k).select("image_id", F.explode(F.array_distinct(at)).alias("key"))
        hits = windows.join(keys, "key").select("image_id", "item_id").distinct()
        parts.append(hits.join(text, "image_id").join(some.select("item_id", "item"), "item_id").where(F.contains("content", "item")).select("image_id", "item_id"))
    return reduce(DataFrame.unionByName, parts) if parts else text.select("image_id", F.col("image_id").alias("item_id")).where("false")
