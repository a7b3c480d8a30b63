"""Comparisons, error rates and error-versus-discard curves."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions import arithmetic
from ..plans.storage import discard, materialise, width


def dense_index(rows: DataFrame, *order: str, name: str = "idx") -> DataFrame:
    """0, 1, 2, ... in the given (total) order without a single-partition window: range partitions, one count each, and a running number inside."""
    spark = rows.sparkSession
    parts = width(spark)
    ranged = materialise(rows.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("_p", F.spark_partition_id()), "ranged")
    counts = sorted((r["_p"], r["n"]) for r in ranged.groupBy("_p").agg(F.count("*").alias("n")).collect())  # one row a partition
    base, total = [], 0
    for p, n in counts:
        base.append((p, total))
        total += n
    table = spark.createDataFrame(base or [(0, 0)], "_p int, _b long")
    inside = F.row_number().over(Window.partitionBy("_p").orderBy(*order)) - 1
    return ranged.withColumn("_i", inside).join(F.broadcast(table), "_p").withColumn(name, (F.col("_b") + F.col("_i")).cast("long")).drop("_p", "_i", "_b")


def mated_all(corpus: DataFrame) -> DataFrame:
    """Every pair of a subject's images: quadratic, the baseline."""
    a, b = corpus.select("subject", "image_id", "path").alias("a"), corpus.select("subject", "image_id", "path").alias("b")
    return a.join(b, (F.col("a.subject") == F.col("b.subject")) & (F.col("a.path") < F.col("b.path"))).select(F.col("a.subject").alias("subject"), F.col("a.image_id").alias("a"), F.col("b.image_id").alias("b"))


def mated_circular(corpus: DataFrame, strategy: str = "window", by: tuple[str, ...] = ()) -> DataFrame:
    """Each image with the next of its subject in path order; the last with the first where there are more than two. ``by`` keeps several collections apart.

    ``window`` sorts each subject in one task. ``index`` numbers all images by (subject, path) over range partitions and joins each number with its successor, so that
    a subject with a large share of all images is no task of its own.
    """
    keys = [*by, "subject"]
    if strategy == "index":
        rows = materialise(dense_index(corpus.select(*keys, "image_id", "path"), *keys, "path"), "numbered")
        ends = rows.groupBy(*keys).agg(F.min_by("image_id", "idx").alias("first"), F.max("idx").alias("last"), F.count("*").alias("n"))
        after = rows.select((F.col("idx") - 1).alias("idx"), F.col("image_id").alias("b"), F.struct(*keys).alias("k2"))
        inner = rows.join(after, "idx").where(F.struct(*keys) == F.col("k2")).select(*keys, F.col("image_id").alias("a"), "b")
        wrap = ends.where("n > 2").join(rows.select(F.col("idx").alias("last"), F.col("image_id").alias("a")), "last").select(*keys, "a", F.col("first").alias("b"))
        return inner.unionByName(wrap)
    own = Window.partitionBy(*keys).orderBy("path")
    whole = own.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = corpus.select(*keys, F.col("image_id").alias("a"), F.lead("image_id").over(own).alias("next"), F.first("image_id").over(whole).alias("first"), F.count("*").over(whole).alias("n"))
    return rows.select(*keys, "a", F.coalesce("next", F.when(F.col("n") > 2, F.col("first"))).alias("b")).where("b is not null")


def mated_counts(corpus: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Pair counts from group sizes alone."""
    n = corpus.groupBy(*by, "subject").agg(F.count("*").alias("n"))
    return n.groupBy(*by).agg(
        F.sum(F.expr("case when n > 2 then n when n = 2 then 1 else 0 end")).alias("circular"), F.sum(F.expr("n * (n - 1) div 2")).alias("all_pairs"), F.count_if(F.col("n") == 1).alias("single_subjects"), F.count_if(F.col("n") == 2).alias("two_subjects")
    )


def _draw(i: Column, seed: int, side: str, n: int) -> Column:
    h = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:{side}:"), i.cast("string"))), 1, 12), 16, 10).cast("long")
    return F.pmod(h, F.lit(n))


def nonmated(corpus: DataFrame, count: int, seed: int = 1, oversample: int = 4) -> DataFrame:
    """``a, b``: ``count`` random pairs of different subjects, unordered and without repeats; all there are, if fewer."""
    return nonmated_by(corpus.withColumn("variant", F.lit("all")), {"all": count}, seed, oversample).select("a", "b")


def nonmated_by(corpus: DataFrame, counts: dict[str, int], seed: int = 1, oversample: int = 4) -> DataFrame:
    """``variant, a, b``: for each variant as many pairs across subjects as ``counts`` says, in the order of their draws.

    Images get a dense index in path order and draws are hashes of their number, so a run is repeatable. Draws go on in rounds until there are enough pairs. Where more than half of all pairs across subjects are
    asked for, draws would repeat themselves: there all of them are listed (at most twice what is asked) and taken in the order of a hash.
    """
    spark = corpus.sparkSession
    indexed = materialise(dense_index(corpus.select("variant", "image_id", "path", "subject"), "variant", "path"), "indexed")
    per = indexed.groupBy("variant", "subject").agg(F.count("*").alias("k"), F.min("idx").alias("lo"))
    sizes = per.groupBy("variant").agg(F.sum("k").alias("n"), F.min("lo").alias("lo"), F.sum(F.col("k").cast("decimal(38,0)") * F.col("k")).alias("own"))
    parts, asked = [], {}
    for r in sizes.collect():  # one row a variant
        possible = (r["n"] ** 2 - int(r["own"])) // 2
        wanted = min(counts.get(r["variant"], 0), possible)
        if wanted and 2 * wanted > possible:
            listed = _across(indexed.where(F.col("variant") == r["variant"]))
            if wanted < possible:
                listed = dense_index(listed.withColumn("h", F.md5(F.concat_ws(":", "a", "b"))), "h", "a", "b", name="k").where(F.col("k") < wanted).select("variant", "a", "b")
            parts.append(listed)
        elif wanted:
            asked[r["variant"]] = (wanted, r["n"], r["lo"])
    if asked:
        parts.append(_drawn(spark, indexed, asked, seed, oversample))
    if not parts:
        return indexed.select("variant", F.col("image_id").alias("a"), F.col("image_id").alias("b")).where("false")
    return reduce(DataFrame.unionByName, parts)


def _drawn(spark, indexed: DataFrame, asked: dict[str, tuple[int, int, int]], seed: int, oversample: int) -> DataFrame:
    left = indexed.select(F.col("idx").alias("x"), F.col("image_id").alias("ia"), F.col("subject").alias("sa"))
    right = indexed.select(F.col("idx").alias("y"), F.col("image_id").alias("ib"), F.col("subject").alias("sb"))
    found, begin = None, {v: 0 for v in asked}
    short = dict(asked)
    while short:
        draws = []
        for v, (wanted, n, lo) in short.items():
            end = begin[v] + max(oversample * wanted, begin[v])  # at least doubled each round
            i = F.col("id")
            draws.append(spark.range(begin[v], end).select(F.lit(v).alias("variant"), "id", (_draw(i, seed, "a", n) + lo).alias("x"), (_draw(i, seed, "b", n) + lo).alias("y")))
            begin[v] = end
        hits = reduce(DataFrame.unionByName, draws).join(left.hint("merge"), "x").join(right.hint("merge"), "y").where("sa <> sb").select("variant", F.least("ia", "ib").alias("a"), F.greatest("ia", "ib").alias("b"), F.col("id").alias("draw"))
        together = hits if found is None else hits.unionByName(found)
        new = materialise(together.groupBy("variant", "a", "b").agg(F.min("draw").alias("draw")), "draws")
        if found is not None:
            discard(found)
        found = new
        have = {r["variant"]: r["n"] for r in found.groupBy("variant").agg(F.count("*").alias("n")).collect()}
        short = {v: x for v, x in asked.items() if have.get(v, 0) < x[0]}
    ranked = dense_index(found, "variant", "draw", name="k")
    base = ranked.groupBy("variant").agg(F.min("k").alias("k0"))
    limit = F.create_map(*[F.lit(x) for v, (wanted, _, _) in asked.items() for x in (v, wanted)])
    return ranked.join(F.broadcast(base), "variant").where(F.col("k") - F.col("k0") < F.try_element_at(limit, F.col("variant"))).select("variant", "a", "b")


def _across(indexed: DataFrame, chunk: int = 1 << 16) -> DataFrame:
    """Every pair across subjects of one variant, no other pair made: by subject each image meets all that come after its subject, in chunks."""
    rows = materialise(dense_index(indexed.select("variant", "subject", "path", "image_id"), "subject", "path", name="at"), "by-subject")
    ends = rows.groupBy("subject").agg((F.max("at") + 1).alias("end"))
    n = rows.count()
    first = rows.join(ends, "subject").where(F.col("end") < n).select("variant", "image_id", F.explode(F.sequence("end", F.lit(n - 1).cast("long"), F.lit(chunk).cast("long"))).alias("lo"))
    every = first.select("variant", F.col("image_id").alias("p"), F.explode(F.sequence("lo", F.least(F.col("lo") + chunk - 1, F.lit(n - 1).cast("long")))).alias("at"))
    return every.join(rows.select("at", F.col("image_id").alias("q")), "at").select("variant", F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"))


def compare(pairs: DataFrame, images: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Pairs with their score and the lesser quality of the two; pairs without a feature on both sides are left out. Sorted merges by hint: the planner takes features for small and would send them through the driver."""
    side = images.select(*by, "image_id", "vec", "q")
    a, b = (side.withColumnsRenamed({"image_id": x, "vec": f"v{x}", "q": f"q{x}"}) for x in "ab")
    low = F.when(F.col("qa").isNull() | F.col("qb").isNull(), F.lit(float("-inf"))).otherwise(F.least("qa", "qb"))
    return pairs.join(a.hint("merge"), [*by, "a"]).join(b.hint("merge"), [*by, "b"]).select(*pairs.columns, arithmetic.score(F.col("va"), F.col("vb")).alias("score"), low.alias("pair_q")).where("score is not null")


def comparisons(images: DataFrame, seed: int = 1) -> DataFrame:
    """Circular mated and equally many non-mated comparisons of the images that could be aligned: ``a, b, mated, score, pair_q``; with a column ``variant``, for each of its values in the same pass."""
    many = "variant" in images.columns
    rows = images if many else images.withColumn("variant", F.lit("all"))
    able = materialise(rows.where("ahi is not null").select("variant", "image_id", "path", "subject", "vec", "q"), "eligible")
    by = ("variant",)
    mated = mated_circular(able, by=by).select("variant", "a", "b", F.lit(True).alias("mated"))
    counts = {r["variant"]: int(r["circular"] or 0) for r in mated_counts(able, by).collect()}  # one row a variant
    other = nonmated_by(able, counts, seed).withColumn("mated", F.lit(False))
    out = compare(mated.unionByName(other), able, by)
    return out if many else out.drop("variant")


def prefix_sums(rows: DataFrame, by: tuple[str, ...], order: str, *values: str) -> DataFrame:
    """``before_v`` (sum of v over smaller ``order`` within the group) and ``total_v`` beside each row, without a single-task window: sums inside range partitions, plus one total a partition and group."""
    ranged = materialise(rows.repartitionByRange(width(rows.sparkSession), *by, order).withColumn("_p", F.spark_partition_id()), "ranged")
    per = ranged.groupBy("_p", *by).agg(*[F.sum(v).alias(f"_{v}") for v in values])  # at most partitions + groups rows
    ahead = Window.partitionBy(*by or [F.lit(0)]).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*by or [F.lit(0)])
    offsets = per.select("_p", *by, *[F.coalesce(F.sum(f"_{v}").over(ahead), F.lit(0)).alias(f"_o{v}") for v in values], *[F.sum(f"_{v}").over(whole).alias(f"total_{v}") for v in values])
    inside = Window.partitionBy("_p", *by).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    out = ranged.withColumns({f"_i{v}": F.coalesce(F.sum(v).over(inside), F.lit(0)) for v in values}).join(F.broadcast(offsets), ["_p", *by])
    return out.select(*rows.columns, *[(F.col(f"_o{v}") + F.col(f"_i{v}")).alias(f"before_{v}") for v in values], *[f"total_{v}" for v in values])


def rates(scores: DataFrame, *by: str) -> DataFrame:
    """``threshold, fnmr, fmr`` at every score that occurs: shares of mated below and of non-mated at or above it.

    Scores are integers of bounded range (2**21 values), so the running sums go over bins, not over comparisons.
    """
    bins = scores.groupBy(*by, F.col("score").alias("threshold")).agg(F.count_if("mated").alias("m"), F.count_if(~F.col("mated")).alias("n"))
    sums = prefix_sums(bins, by, "threshold", "m", "n")
    fnmr = F.try_divide(F.col("before_m").cast("double"), F.col("total_m").cast("double"))
    fmr = F.try_divide((F.col("total_n") - F.col("before_n")).cast("double"), F.col("total_n").cast("double"))
    return sums.select(*by, "threshold", fnmr.alias("fnmr"), fmr.alias("fmr"))


def eer(curve: DataFrame, *by: str) -> DataFrame:
    """Mean of both rates where they are closest (lowest such threshold)."""
    gap = F.struct(F.abs(F.col("fnmr") - F.col("fmr")).alias("g"), "threshold", ((F.col("fnmr") + F.col("fmr")) / 2).alias("eer"))
    return curve.groupBy(*by).agg(F.min(gap).alias("x")).select(*by, F.round("x.eer", 6).alias("eer"), F.col("x.threshold").alias("threshold"))


def fnmr_at(curve: DataFrame, targets: list[float], *by: str, nearest: bool = False) -> DataFrame:
    """FNMR at the largest FMR that does not exceed the target (or the nearest one)."""
    wide = curve.withColumn("target", F.explode(F.array(*[F.lit(float(t)) for t in targets])))
    if nearest:
        pick = F.min(F.struct(F.abs(F.col("fmr") - F.col("target")).alias("g"), "fnmr", "fmr"))
    else:
        wide = wide.where(F.col("fmr") <= F.col("target"))
        pick = F.min(F.struct((-F.col("fmr")).alias("g"), "fnmr", "fmr"))
    return wide.groupBy(*by, "target").agg(pick.alias("x")).select(*by, "target", F.round("x.fnmr", 6).alias("fnmr"), F.round("x.fmr", 6).alias("fmr"))


def start_thresholds(curve: DataFrame, error: str, start: float, *by: str) -> DataFrame:
    """``t``: the fixed threshold of a discard curve, where the error over all comparisons comes nearest to ``start`` (lowest such)."""
    nearest = F.min(F.struct(F.abs(F.col(error) - start).alias("g"), "threshold"))
    return curve.where(F.col(error).isNotNull()).groupBy(*by).agg(nearest.alias("x")).select(*by, F.col("x.threshold").alias("t"))


def edc(scores: DataFrame, error: str = "fnmr", start: float = 0.05, decimals: int | None = None, by: tuple[str, ...] = (), curve: DataFrame | None = None) -> DataFrame:
    """``fraction, until, error``: what is left of the error once the comparisons of lowest quality are discarded; equal qualities go together, and the error holds up to the discarded share ``until``.

    The running sums go over distinct qualities in range partitions; ``decimals`` rounds a continuous quality. ``curve`` are the rates of ``scores``, if known.
    """
    if decimals is not None:
        scores = scores.withColumn("pair_q", F.round("pair_q", decimals))
    t = start_thresholds(rates(scores, *by) if curve is None else curve, error, start, *by)
    wrong = F.col("score") < F.col("t") if error == "fnmr" else F.col("score") >= F.col("t")
    own = scores.where(F.col("mated") == F.lit(error == "fnmr"))
    own = own.join(F.broadcast(t), list(by)) if by else own.join(F.broadcast(t))  # one row a group
    bins = own.groupBy(*by, "pair_q").agg(F.count("*").alias("n"), F.count_if(wrong).alias("w"))
    sums = prefix_sums(bins, by, "pair_q", "n", "w")
    n, gone = F.col("total_n"), F.col("before_n")
    left = (F.col("total_w") - F.col("before_w")).cast("double") / (n - gone)
    return sums.select(*by, (gone.cast("double") / n).alias("fraction"), ((gone + F.col("n")).cast("double") / n).alias("until"), left.alias("error"))


def pauc(curve: DataFrame, high: float = 0.2, normalise: bool = False, by: tuple[str, ...] = ()) -> DataFrame:
    """Area under the steps of a discard curve up to ``high``."""
    step = F.least(F.col("until"), F.lit(high)) - F.col("fraction")
    # Summed in fixed point, so that the order of addition does not show.
    area = F.sum(F.floor(step * F.col("error") * 1e12 + 0.5)).cast("double") / 1e12
    return curve.where(F.col("fraction") < high).groupBy(*by).agg(F.round(area / (high if normalise else 1.0), 6).alias("pauc"))


def measures(scores: DataFrame, by: tuple[str, ...], targets=(0.001, 0.01), start: float = 0.05) -> DataFrame:
    """All measures of an experiment in long form, ``measure, value`` a group: the equal error rate, FNMR at each target FMR, and both areas under discard curves."""
    curve = materialise(rates(scores, *by), "rates")
    out = [eer(curve, *by).select(*by, F.lit("eer").alias("measure"), F.col("eer").alias("value"))]
    out.append(fnmr_at(curve, list(targets), *by).select(*by, F.concat(F.lit("fnmr_at_"), F.col("target").cast("string")).alias("measure"), F.col("fnmr").alias("value")))
    for e in ("fnmr", "fmr"):
        out.append(pauc(edc(scores, e, start, by=by, curve=curve), by=by).select(*by, F.lit(f"pauc_{e}").alias("measure"), F.col("pauc").alias("value")))
    return reduce(DataFrame.unionByName, out)


def changes(measured: DataFrame, of: str = "variant", base: str = "original") -> DataFrame:
    """``change`` of every measure against the ``base`` variant; other grouping columns are kept apart."""
    keys = [c for c in measured.columns if c not in (of, "value")]
    first = measured.where(F.col(of) == base).select(*keys, F.col("value").alias("base"))
    beside = measured.join(F.broadcast(first), keys) if keys else measured.join(F.broadcast(first))  # one row a measure
    return beside.select(*measured.columns, F.round(F.col("value") - F.col("base"), 6).alias("change"))
