"""From overlapping sets to actions: merging, correction by similarity, choice of the kept image and of its subject.

Scores are fixed-point cosines (:mod:`twinfold.functions.arithmetic`), so the thresholds cut the same pairs in every partitioning.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions import arithmetic
from ..plans.components import connected
from ..plans.shipping import ship
from ..plans.storage import materialise
from .detect import DETECTORS, detect, repeated

FLOOR, MARGIN, TAU = 0.40, 0.20, 0.40


def fixed(x: float) -> int:
    return int(x * arithmetic.SCALE + 0.5)


def merge(sets: DataFrame) -> DataFrame:
    """Disjoint sets ``(component, image_id)``: components of the star edges member - smallest member, linear in the members."""
    star = sets.join(sets.groupBy("set_id").agg(F.min("image_id").alias("first")).hint("merge"), "set_id")
    return connected(star.select(F.col("image_id").alias("u"), F.col("first").alias("v"))).select("component", F.col("node").alias("image_id"))


def merge_local(sets: DataFrame, bound: int = 1_000_000) -> DataFrame:
    """The same by one union-find, for at most ``bound`` memberships (checked)."""
    n = sets.limit(bound + 1).count()
    if n > bound:
        raise ValueError(f"more than {bound} memberships; use merge()")

    def run(pdf):
        import pandas as pd

        up: dict = {}

        def find(x):
            while up.setdefault(x, x) != x:
                up[x] = up[up[x]]
                x = up[x]
            return x

        for _, own in pdf.groupby("set_id")["image_id"]:
            own = sorted(own)
            for x in own[1:]:
                a, b = sorted((find(own[0]), find(x)))
                up[b] = a
        return pd.DataFrame({"component": [find(x) for x in up], "image_id": list(up)})

    return sets.groupBy(F.lit(1).alias("g")).applyInPandas(lambda pdf: run(pdf), "component long, image_id long")


_TILE = ["component", "lo", "hi"]


def _in_tiles(components: DataFrame, features: DataFrame, tell: Callable, schema: str, chunk: int) -> DataFrame:
    """What ``tell(component, blocks)`` makes of each tile: two chunks of a component, or one with itself. ``blocks`` are ``(a, b, score, known, real)``: ids of rows and of columns, fixed-point scores as a
    matrix, whether both have a feature, and whether the cell is a pair at all.

    A tile's vectors meet as one product of matrices in an Arrow batch; a block has at most 256 rows. Inner products are exact: in double precision where no sum can reach 2^53, else in 64-bit integers.
    """
    ship(components.sparkSession)
    sizes = components.groupBy("component").agg(F.ceil(F.count("*") / chunk).cast("int").alias("chunks"))
    vec = F.when(F.forall("vec", lambda x: x.isNotNull()), F.col("vec")).alias("vec")
    # sorted merges: the planner takes an array for one number, and ids for few, and would send features and members through the driver
    have = components.join(sizes.hint("merge"), "component").join(features.select("image_id", vec).hint("merge"), "image_id", "left")
    have = have.withColumn("chunk", F.pmod(F.xxhash64("image_id"), F.col("chunks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    dealt = have.select("component", F.least("chunk", "other").alias("lo"), F.greatest("chunk", "other").alias("hi"), "chunk", "image_id", "vec").repartition(*_TILE).sortWithinPartitions(*_TILE, "chunk", "image_id")

    def side(ids, vecs):
        size = np.array([-1 if v is None else len(v) for v in vecs], np.int64)
        width = int(size.max(initial=0))
        x = np.zeros((len(ids), width), np.int64)
        for i, v in enumerate(vecs):
            if v is not None:
                x[i, : len(v)] = v
        most = int(np.abs(x).max(initial=0))
        exact = x.astype(np.float64) if most * most * max(1, width) < 1 << 53 else x
        return ids, exact, np.sqrt((exact * exact).sum(1).astype(np.float64)), size, most

    def blocks(x, y, same):
        width = min(x[1].shape[1], y[1].shape[1])
        fit = x[1].dtype == y[1].dtype == np.float64 and x[4] * y[4] * max(1, width) < 1 << 53
        right = y[1][:, :width].astype(np.float64 if fit else np.int64).T
        for s in range(0, len(x[0]), 256):
            e, skip = s + 256, s if same else 0
            dots = (x[1][s:e, :width].astype(np.float64 if fit else np.int64) @ right[:, skip:]).astype(np.float64)
            norm = x[2][s:e, None] * y[2][skip:]
            known = (norm > 0) & (x[3][s:e, None] == y[3][skip:])
            score = np.floor(np.divide(dots, norm, out=np.zeros_like(dots), where=known) * arithmetic.SCALE + 0.5).astype(np.int64)
            real = x[0][s:e, None] < y[0][skip:] if same else np.ones(score.shape, bool)
            yield x[0][s:e], y[0][skip:], score, known, real

    def tile(key, held):
        ids, vecs, chunks = (np.concatenate([h[i] for h in held]) for i in range(3))
        if key[1] == key[2]:
            own = side(ids, vecs)
            return tell(key[0], blocks(own, own, True))
        first = chunks == key[1]
        return tell(key[0], blocks(side(ids[first], vecs[first]), side(ids[~first], vecs[~first]), False))

    def run(batches):
        key, held, made, rows = None, [], [], 0
        for pdf in batches:
            c, lo, hi = (pdf[k].to_numpy() for k in _TILE)
            ids, vecs, chunks = pdf["image_id"].to_numpy(), pdf["vec"].to_numpy(), pdf["chunk"].to_numpy()
            cuts = np.flatnonzero((c[1:] != c[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])) + 1
            for s, e in zip([0, *cuts], [*cuts, len(pdf)]):
                if s == e:
                    continue
                if (own := (c[s], lo[s], hi[s])) != key:
                    if held:
                        for part in tile(key, held):
                            made.append(part)
                            rows += len(part[0])
                            if rows > 50_000:
                                yield _frame(made, schema)
                                made, rows = [], 0
                    key, held = own, []
                held.append((ids[s:e], vecs[s:e], chunks[s:e]))
        if held:
            made += tile(key, held)
        if made:
            yield _frame(made, schema)

    return dealt.mapInPandas(run, schema)


def _frame(parts: list[tuple], schema: str) -> pd.DataFrame:
    names = [x.split()[0] for x in schema.split(", ")]
    columns = list(zip(*parts))
    return pd.DataFrame({n: pd.concat([pd.Series(x) for x in c], ignore_index=True) for n, c in zip(names, columns)})


def _kind(components: DataFrame) -> str:
    return components.schema["component"].dataType.simpleString()


def pair_scores(components: DataFrame, features: DataFrame, chunk: int = 1024, least: int | None = None) -> DataFrame:
    """All pairs inside components with their score; null where a feature is missing; with ``least`` only pairs that reach it. ``features(image_id, vec)``.

    A large component is cut to chunks and its pairs to tiles of two chunks, which are keys of their own: no task holds more than a tile.
    """

    def tell(component, blocks):
        for a, b, score, known, real in blocks:
            i, j = np.nonzero(real if least is None else real & known & (score >= least))
            if len(i):
                u, v = a[i], b[j]
                yield np.full(len(i), component), np.minimum(u, v), np.maximum(u, v), pd.arrays.IntegerArray(score[i, j], ~known[i, j])

    return _in_tiles(components, features, tell, f"component {_kind(components)}, a long, b long, score long", chunk)


def spanning(components: DataFrame, features: DataFrame, least: int, chunk: int = 1024) -> DataFrame:
    """``u, v``: of each tile, every image that has a pair with at least ``least`` beside the smallest image it reaches by such pairs: the same connections as all these pairs, in as many rows as images."""

    def tell(component, blocks):
        up = {}

        def find(x):
            while up.setdefault(x, x) != x:
                up[x] = up[up[x]]
                x = up[x]
            return x

        for a, b, score, known, real in blocks:
            hit = real & known & (score >= least)
            for i in np.flatnonzero(hit.any(axis=1)):
                near = b[hit[i]]
                roots = {find(x) for x in (int(a[i]), *near.tolist())}
                low = min(roots)
                for r in roots:
                    up[r] = low
        if up:
            u = np.fromiter(up, np.int64, len(up))
            yield u, np.array([find(x) for x in u.tolist()], np.int64)

    return _in_tiles(components, features, tell, "u long, v long", chunk)


def _failing(components: DataFrame, features: DataFrame, tau: float, missing: str, chunk: int = 1024) -> DataFrame:
    """``image_id, some, every`` of each image and tile: whether one of its pairs fails, and whether all do. Pairs are not listed."""
    expel, least = missing == "expel", fixed(tau)

    def tell(component, blocks):
        for a, b, score, known, real in blocks:
            fails = np.where(known, score < least, expel)
            bad, good = fails & real, ~fails & real
            for ids, axis in ((a, 1), (b, 0)):
                has = real.any(axis=axis)
                yield ids[has], bad.any(axis=axis)[has], ~good.any(axis=axis)[has]

    return _in_tiles(components, features, tell, "image_id long, some boolean, every boolean", chunk)


def correct(components: DataFrame, features: DataFrame, tau: float = TAU, rule: str = "strict", missing: str = "keep") -> DataFrame:
    """Components without their false positives; what shrinks to one image dissolves.

    ``strict``: both images of a pair below ``tau`` leave. ``lenient``: an image leaves if none of its pairs passes. ``split``: passing pairs form new components. A pair
    without a score is not below; ``missing='expel'`` says it is.
    """
    if rule == "none":
        return components
    if rule == "split":
        fails = F.coalesce(F.col("score") < fixed(tau), F.lit(missing == "expel"))
        good = pair_scores(components, features).where(~fails).select(F.col("a").alias("u"), F.col("b").alias("v"))
        return connected(good).select("component", F.col("node").alias("image_id"))
    out = F.bool_or("some") if rule == "strict" else F.bool_and("every")
    gone = _failing(components, features, tau, missing).groupBy("image_id").agg(out.alias("out")).where("out").select("image_id")
    left = components.join(gone.hint("merge"), "image_id", "left_anti")
    return repeated(left, "component").select("component", "image_id")


def threshold_sweep(components: DataFrame, features: DataFrame, taus: list[float], rule: str = "strict") -> DataFrame:
    """Released images per threshold, in one pass over the pair scores."""
    scores = pair_scores(components, features).withColumn("tau", F.explode(F.array(*[F.lit(float(t)) for t in taus])))
    fails = F.coalesce(F.col("score") < F.floor(F.col("tau") * float(arithmetic.SCALE) + 0.5), F.lit(False))
    each = scores.select("tau", F.explode(F.array("a", "b")).alias("image_id"), fails.alias("fails"))
    out = F.bool_or("fails") if rule == "strict" else F.bool_and("fails")
    return each.groupBy("tau", "image_id").agg(out.alias("out")).groupBy("tau").agg(F.count_if("out").alias("released"), F.count("*").alias("images"))


def sample_sets(sets: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """``n`` sets in the order of a hash, for inspection; the same on every run."""
    ids = sets.select("set_id").distinct().orderBy(F.md5(F.concat(F.lit(f"{seed}:"), "set_id")), "set_id").limit(n)
    return sets.join(ids, "set_id", "left_semi")


def _worth() -> Column:
    """Quality with NaN and missing as minus infinity."""
    q = F.col("q")
    return F.when(q.isNull() | F.isnan(q), F.lit(float("-inf"))).otherwise(q)


def keep_first(sets: DataFrame, corpus: DataFrame, key: str = "set_id") -> DataFrame:
    return sets.join(corpus.select("image_id", "path"), "image_id").groupBy(key).agg(F.min(F.struct("path", "image_id")).alias("k")).select(key, F.col("k.image_id").alias("kept"))


def keep_random(sets: DataFrame, corpus: DataFrame, seed: int = 0, key: str = "set_id") -> DataFrame:
    draw = F.md5(F.concat(F.lit(f"{seed}:"), "path"))
    return sets.join(corpus.select("image_id", "path"), "image_id").groupBy(key).agg(F.min(F.struct(draw.alias("d"), "path", "image_id")).alias("k")).select(key, F.col("k.image_id").alias("kept"))


def keep_best(components: DataFrame, images: DataFrame) -> DataFrame:
    """``(component, kept)``: best quality, then first path. A partial minimum over a struct, no sort."""
    return components.join(images.select("image_id", "path", "q").hint("merge"), "image_id").groupBy("component").agg(F.min(F.struct((-_worth()).alias("w"), "path", "image_id")).alias("k")).select("component", F.col("k.image_id").alias("kept"))


def reference(images: DataFrame, sets: DataFrame) -> DataFrame:
    """Images that no set has ever held, corrected or not."""
    return images.join(sets.select("image_id").distinct().hint("merge"), "image_id", "left_anti")


def subject_scores(kept: DataFrame, involved: DataFrame, references: DataFrame, features: DataFrame, strategy: str = "pairs") -> DataFrame:
    """Mean similarity of each kept image to the reference images of each involved subject: ``component, kept, subject, mean, n``.

    ``pairs`` scores every (kept, reference) pair. ``centroid`` uses that a mean of cosines is one product with the mean unit vector: references are read once per subject, whatever the number of
    sets. Only references of involved subjects are read (semi join). Subjects without usable references are no candidates.
    """
    vec = features.where("vec is not null").select("image_id", "vec")
    wanted = references.join(involved.select("subject").distinct(), "subject", "left_semi").select("image_id", "subject").join(vec.hint("merge"), "image_id")
    own = vec.withColumnRenamed("image_id", "kept").withColumnRenamed("vec", "own")
    asked = kept.join(own.hint("merge"), "kept").join(involved.hint("merge"), "component")
    if strategy == "pairs":
        pairs = asked.join(wanted.select("subject", "vec"), "subject").withColumn("score", arithmetic.score(F.col("own"), F.col("vec")))
        sums = pairs.where("score is not null").groupBy("component", "kept", "subject").agg(F.sum("score").alias("total"), F.count("*").alias("n"))
        return sums.select("component", "kept", "subject", (F.col("total").cast("double") / F.col("n")).alias("mean"), "n")
    unit = wanted.where(arithmetic.dot(F.col("vec"), F.col("vec")) > 0).withColumn("u", _unit("vec"))
    flat = unit.select("subject", F.posexplode("u").alias("d", "x")).groupBy("subject", "d").agg(F.sum("x").alias("x"), F.count("*").alias("n"))
    centre = flat.groupBy("subject").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "x"))), lambda p: p["x"]).alias("centre"), F.max("n").alias("n"))
    at = asked.where(arithmetic.dot(F.col("own"), F.col("own")) > 0).join(centre, "subject")
    value = arithmetic.dot(_unit("own"), F.col("centre")).cast("double") / F.lit(float(arithmetic.SCALE)) / F.col("n")
    return at.select("component", "kept", "subject", value.alias("mean"), "n")


def _unit(c: str) -> Column:
    """Unit vector in fixed point. A zero vector has none: its components are null, not an error, since the planner may make units before it drops zero vectors."""
    norm = F.sqrt(arithmetic.dot(F.col(c), F.col(c)).cast("double"))
    return F.transform(F.col(c), lambda x: F.floor(F.try_divide(x.cast("double"), norm) * F.lit(float(arithmetic.SCALE)) + 0.5).cast("long"))


def choose(kept: DataFrame, scores: DataFrame, features: DataFrame, floor: float = FLOOR, margin: float = MARGIN, single_candidate: str = "accept") -> DataFrame:
    """``component, kept, target, reason``: the best subject if its mean reaches the floor and leads by the margin; target null otherwise."""
    ranked = scores.withColumn("r", F.row_number().over(Window.partitionBy("component").orderBy(F.desc("mean"), "subject")))
    best = ranked.where("r = 1").select("component", F.col("subject").alias("best"), F.col("mean").alias("top"))
    second = ranked.where("r = 2").select("component", F.col("mean").alias("next"))
    have = features.where("vec is not null").select(F.col("image_id").alias("kept"), F.lit(True).alias("has"))
    all_ = kept.join(best.hint("merge"), "component", "left").join(second.hint("merge"), "component", "left").join(have.hint("merge"), "kept", "left")
    lead = F.coalesce(F.col("top") - F.col("next") >= float(fixed(margin)), F.lit(single_candidate == "accept"))
    reason = (
        F.when(F.col("has").isNull(), "no_feature").when(F.col("best").isNull(), "no_candidate").when(F.col("top") < float(fixed(floor)), "below_floor").when(~lead, "thin_margin").otherwise("assigned")
    )
    return all_.select("component", "kept", F.when(reason == "assigned", F.col("best")).alias("target"), reason.alias("reason"))


def actions(
    signed: DataFrame, detectors=DETECTORS, variants=("original", "aligned"), tau: float = TAU, rule: str = "strict", floor: float = FLOOR, margin: float = MARGIN, strategy: str = "centroid", exact_first: bool = True,
    contents: DataFrame | None = None,
) -> DataFrame:
    """The action list: ``image_id, path, action, reason, from_subject, to_subject`` for every image that is in a decided set.

    Exact single-subject copies fall to the first path; near sets of what is left merge, are corrected, keep their best image, and, where they cross subjects, give it to the subject it resembles or to none.
    Sets, members and kept images may be as many as the collection: they meet in sorted merges by hint, none goes through the driver.
    """
    raw = materialise(detect(signed, detectors, variants, contents=contents), "sets")
    narrow = signed.select("image_id", "path", "subject", "q")
    parts: list[DataFrame] = []
    near = raw
    if exact_first and "digest" in detectors:
        e = raw.where("detector = 'digest'")
        intra = e.join(narrow.select("image_id", "subject", "path").hint("merge"), "image_id")
        one = intra.groupBy("set_id").agg(F.count_distinct("subject").alias("k"), F.min("path").alias("first")).where("k = 1")
        judged = materialise(intra.join(one.hint("merge"), "set_id").select("image_id", (F.col("path") == F.col("first")).alias("kept")), "exact")
        gone = judged.where("not kept").select("image_id")
        near = repeated(raw.join(gone.hint("merge"), "image_id", "left_anti"), "set_id")  # the sets of what is left, without detecting again
        parts.append(judged.select("image_id", F.when(F.col("kept"), "keep").otherwise("remove").alias("action"), F.lit("exact_copy").alias("reason"), F.lit(None).cast("string").alias("to_subject")))
    solved = materialise(correct(materialise(merge(near), "components"), signed, tau, rule), "corrected")
    kept = materialise(keep_best(solved, signed), "kept")
    members = materialise(solved.join(narrow.select("image_id", "subject").hint("merge"), "image_id"), "members")
    kinds = members.groupBy("component").agg(F.count_distinct("subject").alias("k"))
    inter = materialise(kinds.where("k > 1").select("component"), "inter")
    involved = members.join(inter.hint("merge"), "component", "left_semi").select("component", "subject").distinct()
    asked = kept.join(inter.hint("merge"), "component", "left_semi")
    # tables of their own: each is read several times below, and one plan of them all would be large on the driver
    scores = materialise(subject_scores(asked, involved, reference(narrow, raw), signed, strategy), "scores")
    chosen = choose(asked, scores, signed, floor, margin)
    others = members.join(kept.select(F.col("kept").alias("image_id")).hint("merge"), "image_id", "left_anti").select("image_id", F.lit("remove").alias("action"), F.lit("lower_quality").alias("reason"), F.lit(None).cast("string").alias("to_subject"))
    single = kept.join(inter.hint("merge"), "component", "left_anti").select(F.col("kept").alias("image_id"), F.lit("keep").alias("action"), F.lit("best_quality").alias("reason"), F.lit(None).cast("string").alias("to_subject"))
    placed = chosen.join(narrow.select(F.col("image_id").alias("kept"), "subject").hint("merge"), "kept").select(
        F.col("kept").alias("image_id"), F.when(F.col("target").isNull(), "remove").when(F.col("target") != F.col("subject"), "move").otherwise("keep").alias("action"), "reason", F.col("target").alias("to_subject")
    )
    second = materialise(others.unionByName(single).unionByName(placed), "decided")
    out = second
    if parts:  # an exact copy that stayed and met near copies is decided by these
        out = second.unionByName(parts[0].join(second.select("image_id").hint("merge"), "image_id", "left_anti"))
    return out.join(narrow.select("image_id", "path", F.col("subject").alias("from_subject")).hint("merge"), "image_id").select("image_id", "path", "action", "reason", "from_subject", "to_subject")


def preservative(corpus: DataFrame, acts: DataFrame) -> DataFrame:
    """The corpus after its actions."""
    gone = acts.where("action = 'remove'").select("image_id")
    moved = acts.where("action = 'move'").select("image_id", "to_subject")
    return corpus.join(gone.hint("merge"), "image_id", "left_anti").join(moved.hint("merge"), "image_id", "left").withColumn("subject", F.coalesce("to_subject", "subject")).drop("to_subject")


def full_removal(corpus: DataFrame, sets: DataFrame) -> DataFrame:
    """The corpus without any image of any set."""
    return corpus.join(sets.select("image_id").distinct().hint("merge"), "image_id", "left_anti")
