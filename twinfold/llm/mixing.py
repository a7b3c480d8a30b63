"""Mixing sources to target weights by entropy balancing.

Each document gets a rate, the expected number of its copies in the mix. Among all rates that meet the token
constraints the mix takes those of least relative entropy to "everything once"; their dual is a concave function
of one multiplier a source plus one a moment, so rates are exponentially tilted, q = min(cap, exp(a_source + b*z)).
Newton steps maximise the dual: each step is one aggregation over the (source, size) histogram that returns a few sums a source,
never rows. z is the standardised log size; its constraint (the mix keeps the corpus's token-weighted mean log size)
is elastic, since caps may make it infeasible. Rates are then rounded to whole copies class by class, carrying what rounding left over from
large documents to small ones, so that every source ends within about one small document of its target.

Defined results: null text has size 0 and takes nothing; a null source is a source of its own, last in order; a source without
words has target 0; repeated rows are documents of their own; an empty table gives an empty result. Other columns are not read;
those of the input survive in :func:`mix` whatever their names, except those called as the results (in any case), which are replaced. A dual that does not converge is an error. The table of sources is held on the driver: at most
``max_sources`` of them, else an error.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..plans.columns import Carried
from ..plans.storage import discard, materialise, width

WORD = r"[^\x20\x09-\x0D]+"
RESULT = ("size", "source_size", "target", "rate", "copies", "taken")


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def water_fill(sizes: list[float], weights: list[float], total: float, cap: float) -> list[float]:
    """Shares of ``total`` by weight, none above ``cap`` times its size; what is cut off is shared again."""
    targets, free = [0.0] * len(sizes), list(range(len(sizes)))
    left = total
    while free:
        whole = sum(weights[i] for i in free)
        over = [i for i in free if left * weights[i] / whole > cap * sizes[i]]
        if not over:
            for i in free:
                targets[i] = left * weights[i] / whole
            break
        for i in over:
            targets[i] = cap * sizes[i]
            left -= targets[i]
            free.remove(i)
    return targets


def source_targets(sources: list[str | None], sizes: list[float], weights=(5, 2, 1), share: float = 1.5, cap: float = 2.0) -> list[float]:
    """Weights repeat over the sources in code-point order, null last."""
    order = sorted(range(len(sources)), key=lambda i: (sources[i] is None, sources[i] or ""))
    own = [0.0] * len(sources)
    for k, i in enumerate(order):
        own[i] = float(weights[k % len(weights)])
    return water_fill(sizes, own, share * sum(sizes), cap)


def _key(c: str = "source") -> Column:
    return F.coalesce(F.concat(F.lit("="), F.col(c).cast("string")), F.lit("null"))


def balance(hist: DataFrame, targets: dict[str, float], cap: float, moment_weight: float = 0.05, tol: float = 1e-7, max_steps: int = 40):
    """Newton on the dual. ``hist(_s, size, z, n)``; returns ({source: a}, b). Sources that need their cap take exactly it."""
    spark = hist.sparkSession
    totals = {r["_s"]: (r["t"], r["tz"]) for r in hist.groupBy("_s").agg(F.sum(F.col("n") * F.col("size")).alias("t"), F.sum(F.col("n") * F.col("size") * F.col("z")).alias("tz")).collect()}
    live = [s for s, (t, _) in totals.items() if t > 0 and 0 < targets[s] < cap * t * (1 - 1e-12)]
    a = {s: math.log(targets[s] / totals[s][0]) if s in set(live) else (math.log(cap) if targets[s] > 0 else -700.0) for s in totals}
    b, whole = 0.0, sum(targets[s] for s in live)
    corpus = sum(totals[s][0] for s in totals)
    goal = whole * sum(totals[s][1] for s in totals) / corpus if corpus else 0.0
    ridge = whole * moment_weight
    if not live:
        return a, b
    for _ in range(max_steps):
        now = spark.createDataFrame([(s, float(a[s])) for s in live], "_s string, a double")
        raw = F.exp(F.col("a") + F.lit(b) * F.col("z"))
        w = F.col("n") * F.col("size")
        open_ = F.when(raw < cap, w * raw).otherwise(0.0)
        q = w * F.least(raw, F.lit(cap))
        rows = hist.join(now, "_s").groupBy("_s").agg(
            F.sum(q).alias("g"), F.sum(q * F.col("z")).alias("gz"), F.sum(open_).alias("h"),
            F.sum(open_ * F.col("z")).alias("hz"), F.sum(open_ * F.col("z") * F.col("z")).alias("hzz"),
        ).collect()
        miss = {r["_s"]: targets[r["_s"]] - r["g"] for r in rows}
        slope = goal - sum(r["gz"] for r in rows) - ridge * b
        far = max(*[abs(miss[r["_s"]]) / targets[r["_s"]] for r in rows], abs(slope) / whole)
        if far < tol:
            break
        # The Hessian is an arrow (diagonal by source, one border row): solve by its Schur complement.
        h = {r["_s"]: max(r["h"], 1e-9 * targets[r["_s"]]) for r in rows}
        schur = ridge + sum(r["hzz"] - r["hz"] ** 2 / h[r["_s"]] for r in rows)
        db = float(np.clip((slope - sum(r["hz"] * miss[r["_s"]] / h[r["_s"]] for r in rows)) / max(schur, 1e-12), -0.5, 0.5))
        for r in rows:
            a[r["_s"]] += float(np.clip((miss[r["_s"]] - r["hz"] * db) / h[r["_s"]], -1.0, 1.0))
        b += db
    else:
        if far > 1e-3:
            raise RuntimeError(f"the dual is {far:.2g} from its optimum after {max_steps} steps")
    return a, b


def whole_copies(classes: list[tuple[int, int, int, float]], target: float, cap: float) -> dict[int, tuple[int, int]]:
    """Per size class (class, n, tokens, expected tokens) the copies all get and how many get one more, largest class first."""
    out, carry = {}, 0.0
    for cls, n, tokens, want in sorted(classes, reverse=True):
        if not tokens:
            out[cls] = (1 if target > 0 else 0, 0)
            continue
        mean = tokens / n
        times = min(cap * n, max(0, round((want + carry) / mean)))
        carry += want - times * mean
        out[cls] = (int(times // n), int(times % n))
    return out


def mix(docs: DataFrame, weights=(5, 2, 1), share: float = 1.5, cap: int = 2, size: Column | None = None, max_sources: int = 1_000_000) -> DataFrame:
    """``docs(doc_id, text, source, ...)`` with size, source_size, target, rate, copies and taken beside each document; ``size``, a column of ``docs``, takes the place of counting the words of ``text``.

    What a document gets follows from a small table, one row a source and size class: whole copies, and the last document of the class's order that gets one more. So the documents are not shuffled.
    """
    own = ("doc_id", "source") if size is not None else ("doc_id", "source", "text")
    carried = Carried(docs, *own, taken=RESULT, **({} if size is None else {"counted": size}))
    n = word_count(F.col("text")) if size is None else F.col("counted").cast("long")
    salts = max(16, width(docs.sparkSession))
    order = F.xxhash64("doc_id", "_s", "size")  # of the document, so that reruns agree; rows only break ties of equal documents
    rows = carried.rows.withColumns({"size": n, "_s": _key()}).withColumns({"_o": order, "_uid": F.monotonically_increasing_id()}).withColumns(
        {"_salt": F.pmod(F.xxhash64("_o"), F.lit(salts)).cast("int"), "_c": F.when(F.col("size") < 32, F.col("size")).otherwise(F.floor(8 * F.log2("size")) - 8).cast("int")}
    )
    rows = materialise(rows, "documents")
    table, rate, few = _plan(rows.select(*_PLACE, "_s", "_c", "source", "size"), weights, share, cap, max_sources)
    copies = (F.col("_base") + F.coalesce(F.struct(*_PLACE) <= F.col("_edge"), F.lit(False)).cast("int")).cast("int")
    done = rows.join(F.broadcast(table) if few else table, ["_s", "_c"]).withColumn("copies", copies)
    return done.withColumn("rate", rate).withColumn("taken", F.col("size") * F.col("copies")).select(*carried.back(), *RESULT)


#: A document's place in its size class.
_PLACE = ("_salt", "_o", "doc_id", "_uid")


def _plan(rows: DataFrame, weights, share: float, cap: int, max_sources: int) -> tuple[DataFrame, Column, bool]:
    """``_s, _c, source_size, target, a, _base, _edge`` a source and size class, the rate as an expression, and whether the table is small."""
    spark = rows.sparkSession
    sources = rows.groupBy("_s").agg(F.first("source").alias("source"), F.sum("size").alias("t")).limit(max_sources + 1).collect()
    if len(sources) > max_sources:
        raise ValueError(f"more than {max_sources} sources: merge them or raise max_sources")
    targets = dict(zip([r["_s"] for r in sources], source_targets([r["source"] for r in sources], [float(r["t"]) for r in sources], weights, share, float(cap))))
    moments = rows.where("size > 0").agg(*[F.sum(F.col("size") * F.log("size") ** k).alias(f"m{k}") for k in (0, 1, 2)]).first()
    mean = (moments["m1"] or 0.0) / (moments["m0"] or 1.0)
    spread = math.sqrt(max(1e-12, (moments["m2"] or 0.0) / (moments["m0"] or 1.0) - mean**2)) if moments["m0"] else 1.0
    spread = max(spread, 1e-3)
    z = ((F.log(F.greatest("size", F.lit(1))) - mean) / spread).alias("z")
    hist = materialise(rows.groupBy("_s", "_c", "size").agg(F.count("*").cast("double").alias("n")).select("*", z), "histogram")
    a, b = balance(hist, targets, float(cap))
    schema = "_s string, source_size long, target double, a double"
    tilt = spark.createDataFrame([(r["_s"], int(r["t"]), float(targets[r["_s"]]), float(a[r["_s"]])) for r in sources], schema)
    rate = F.least(F.lit(float(cap)), F.exp(F.col("a") + F.lit(b) * F.col("z")))
    rate = F.when(F.col("target") >= cap * F.col("source_size"), F.lit(float(cap))).otherwise(rate)
    classes: dict[str, list] = {r["_s"]: [] for r in sources}
    for r in hist.join(tilt, "_s").groupBy("_s", "_c").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("size")).alias("t"), F.sum(F.col("n") * F.col("size") * rate).alias("w")).collect():
        classes[r["_s"]].append((r["_c"], int(r["n"]), int(r["t"]), r["w"]))
    chosen = {s: whole_copies(own, targets[s], cap) for s, own in classes.items()}
    # A document's rank in its class: first rank of its salt, from counts, plus its place in the salt.
    cells = rows.groupBy("_s", "_c", "_salt").agg(F.count("*").alias("_n"))
    firsts = cells.select("_s", "_c", "_salt", (F.sum("_n").over(Window.partitionBy("_s", "_c").orderBy("_salt")) - F.col("_n")).alias("_f"))
    inside = Window.partitionBy("_s", "_c", "_salt").orderBy(*_PLACE[1:])
    ranked = materialise(rows.withColumn("_r", F.row_number().over(inside) - 1).join(firsts, ["_s", "_c", "_salt"]).select(*_PLACE, "_s", "_c", "size", (F.col("_f") + F.col("_r")).alias("_rank")), "ranked")

    def taken(now: dict) -> DataFrame:
        table = spark.createDataFrame([(s, c, k, n) for s, own in now.items() for c, (k, n) in own.items()], "_s string, _c int, _base int, _more long")
        copies = F.col("_base") + (F.col("_rank") < F.col("_more")).cast("int")
        return ranked.join(table, ["_s", "_c"]).withColumn("copies", copies.cast("int"))

    for _ in range(2):  # what sizes differ within a class is known now; the rest goes to the classes it fits
        got = {r["_s"]: r["t"] for r in taken(chosen).groupBy("_s").agg(F.sum(F.col("size") * F.col("copies")).alias("t")).collect()}
        for s, own in classes.items():
            rest = targets[s] - got.get(s, 0)
            for cls, n, tokens, _ in sorted(own, reverse=True):
                if not tokens:
                    continue
                base, more = chosen[s][cls]
                step = int(np.clip(int(rest / (tokens / n)), -(base * n + more), cap * n - base * n - more))
                times = base * n + more + step
                chosen[s][cls] = (times // n, times % n)
                rest -= step * tokens / n
    flat = [(s, c, k, n) for s, own in chosen.items() for c, (k, n) in own.items()]
    table = spark.createDataFrame(flat, "_s string, _c int, _base int, _more long")
    edges = ranked.join(table.where("_more > 0"), ["_s", "_c"]).where("_rank = _more - 1").select("_s", "_c", F.struct(*_PLACE).alias("_edge"))
    whole = materialise(table.join(tilt, "_s").join(edges, ["_s", "_c"], "left").select("_s", "_c", "source_size", "target", "a", "_base", "_edge"), "classes")
    discard(ranked, hist)
    z = (F.log(F.greatest("size", F.lit(1))) - mean) / spread
    tilted = F.least(F.lit(float(cap)), F.exp(F.col("a") + F.lit(b) * z))
    return whole, F.when(F.col("target") >= cap * F.col("source_size"), F.lit(float(cap))).otherwise(tilted), len(flat) <= 200_000


def replicate(mixed: DataFrame, columns: list[str]) -> DataFrame:
    """Each document as many times as its copies say."""
    return mixed.where("copies > 0").select(*columns, F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy")).drop("copy")
