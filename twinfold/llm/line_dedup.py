"""Removal of repeated line runs by a suffix array over the corpus of lines, in DataFrame functions only.

The corpus is one sequence of line ids a document (128-bit hashes of the trimmed line; blank lines are no units). Prefix doubling ranks its suffixes: lines that occur at least twice are numbered in order, and the
rank of 2h lines is the number of the pair (rank of h lines here, rank of h lines h further on) in the order of pairs, over range partitions. Suffixes whose first h lines occur once are in their final place and
take no further part, so each round sorts only what still repeats, and doubling ends when every rank is unique: after log2 of the longest repeat. Suffixes of equal rank at depth h are an interval of the suffix
array with a common prefix of at least h lines; equal pairs of ranks (at a start, and so far on that both together span n lines) are the intervals of the depths between powers of two.

A run counts as repeated from ``min_words`` words on. A suffix that is not the first of the corpus in an interval starts a later copy of the interval's common prefix. Of each suffix the deepest such interval of a
doubling depth is taken, which for runs of ``min_words`` lines and more covers every line of every copy; for shorter runs, the intervals of the shortest run that starts, and that ends, at a line and
has the words. Overlapping and adjoining copies make the maximal repeated runs. They are deleted, with blank lines between two deleted ones; first copies (in the order of doc_id, then row) stay.

Defined results: null text stays null, empty text stays empty; a document all of whose lines go has the empty text and ``emptied`` true; ties in doc_id are ordered by row; repeated rows are later copies; null doc_ids
come last; very long documents are only long sequences; an empty table gives an empty result; other columns, whatever their names, are carried along, except those named like a result.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..plans.bitmaps import reduce_by, split_by
from ..plans.columns import Carried
from ..plans.storage import discard, materialise, width

WORD = r"\S+"
RESULT = ("lines", "removed_lines", "emptied")


def _here(lo: int, hi: int):
    """The lines from ``lo`` to ``hi`` after this one of the same document."""
    return Window.partitionBy("uid").orderBy("u").rangeBetween(lo, hi)


def _order() -> Column:
    """The order of the corpus."""
    return F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "uid", "u")


def line_units(rows: DataFrame) -> DataFrame:
    """(uid, doc_id, pos, u, a, b, w): the non-blank lines of ``rows(uid, doc_id, text)``: place among all lines and among these, 128-bit id, words."""
    lines = F.transform(F.split("text", "\n", -1), lambda x, i: F.struct(i.alias("pos"), F.trim(x).alias("line")))
    line = F.col("x.line")
    return rows.select("uid", "doc_id", F.posexplode(F.filter(lines, lambda x: x["line"].rlike(r"\S"))).alias("u", "x")).select(
        "uid", "doc_id", "x.pos", "u", F.xxhash64(line).alias("a"), F.xxhash64(F.lit(7), line).alias("b"), F.regexp_count(line, F.lit(WORD)).cast("long").alias("w")
    )


def ranked(rows: DataFrame, *keys: str) -> DataFrame:
    """The keys that occur at least twice, with ``rank`` in their order, and their first member ``low`` in the order of the corpus.

    Range partitions are sorted and numbered apart (the number has gaps); written at once, so that a lost task repeats the same numbers.
    """
    many = rows.groupBy(*keys).agg(F.count("*").alias("n"), F.min(_order()).alias("low")).where("n > 1").drop("n")
    return materialise(many.repartitionByRange(width(rows.sparkSession), *keys).sortWithinPartitions(*keys).withColumn("rank", F.monotonically_increasing_id()), "ranks")


def _renamed(rows: DataFrame, ranks: DataFrame, keys: list[str], *more: str) -> DataFrame:
    """(uid, doc_id, u, r, later): suffixes with their new rank; ``later`` says that the interval has an earlier member."""
    first = (F.col("uid") == F.col("low.uid")) & (F.col("u") == F.col("low.u"))
    return materialise(rows.join(ranks, keys).select("uid", "doc_id", "u", F.col("rank").alias("r"), (~first).alias("later"), *more), "suffixes")


def suffix_ranks(units: DataFrame) -> list[DataFrame]:
    """For depths 1, 2, 4, ... lines the suffixes whose first lines so far occur at least twice: ``uid, doc_id, u, r, later`` (and pos, w at depth 1). The last depth is empty."""
    named = ranked(units, "a", "b")
    levels = [_renamed(reduce_by(units, named, "a"), named, ["a", "b"], "pos", "w")]
    discard(named)
    while not levels[-1].isEmpty():
        depth = 1 << (len(levels) - 1)
        further = F.first("r").over(_here(depth, depth))
        pairs = materialise(levels[-1].select("uid", "doc_id", "u", "r", further.alias("r2")).where("r2 is not null"), "pairs")
        named = ranked(pairs, "r", "r2")
        levels.append(_renamed(pairs, named, ["r", "r2"]))
        discard(pairs, named)
    return levels


def _deep_copies(levels: list[DataFrame], min_words: int) -> DataFrame | None:
    """(uid, us, ue): of each suffix the deepest interval of at least ``min_words`` lines in which it is not the first."""
    deep = [t.where("later").select("uid", "u", F.lit(1 << k).alias("depth")) for k, t in enumerate(levels[:-1]) if 1 << k >= min_words]
    if not deep:
        return None
    return reduce(DataFrame.unionByName, deep).groupBy("uid", "u").agg(F.max("depth").alias("depth")).select("uid", F.col("u").alias("us"), (F.col("u") + F.col("depth") - 1).alias("ue"))


def _short_copies(levels: list[DataFrame], min_words: int) -> DataFrame:
    """(uid, us, ue): later copies among the shortest runs of ``min_words`` words that start, or end, at a line. Such a run has at most ``min_words`` lines."""
    need = min_words.bit_length()  # depths up to the largest power of two within min_words lines
    rows = levels[0].select("uid", "doc_id", "u", "w", F.col("r").alias("r0"))
    for k, t in enumerate(levels[1:need], 1):
        rows = rows.join(t.select("uid", "u", F.col("r").alias(f"r{k}")), ["uid", "u"], "left")
    have = min(need, len(levels))
    around: dict[str, Column] = {}

    def at(c: str, d: int) -> Column:
        """The value ``d`` lines on; null where that line occurs only once."""
        if d == 0:
            return F.col(c)
        around[f"{c}_{d}"] = F.first(c).over(_here(d, d))
        return F.col(f"{c}_{d}")

    def run(back: bool) -> Column:
        """The shortest run of enough words from here (or up to here) as struct(us, ue, n, x, y); null where there is none that may repeat."""
        words, out, open_ = F.lit(0).cast("long"), F.lit(None), []
        for n in range(1, min_words + 1):
            words = words + at("w", 1 - n if back else n - 1)  # null from the first line on that cannot be part of a repeat
            k = n.bit_length() - 1
            if k >= have:
                break
            first = 1 - n if back else 0
            x, y = at(f"r{k}", first), at(f"r{k}", first + n - (1 << k))
            enough = words >= min_words
            if back:  # what is enough without its last line as well is not the shortest run from its start: only that adds something
                enough = enough & (words - F.col("w") >= min_words)
            made = F.when(enough & x.isNotNull() & y.isNotNull(), F.struct((F.col("u") + first).alias("us"), (F.col("u") + first + n - 1).alias("ue"), F.lit(n).alias("n"), x.alias("x"), y.alias("y")))
            open_.append((words >= min_words, made))
        for reached, made in reversed(open_):  # the first length that has the words decides
            out = F.when(reached, made).otherwise(out)
        return out

    runs = F.array_compact(F.array(run(False), run(True)))
    found = rows.withColumns(around).select("uid", "doc_id", F.explode(runs).alias("x")).select("uid", "doc_id", "x.*")
    windows = materialise(found.withColumn("u", F.col("us")), "windows")
    many = windows.groupBy("n", "x", "y").agg(F.count("*").alias("k"), F.min(_order()).alias("low")).where("k > 1").select("n", "x", "y", F.col("low.uid").alias("u0"), F.col("low.u").alias("s0"))
    firsts = materialise(many, "firsts")
    return windows.join(firsts, ["n", "x", "y"]).where("uid <> u0 or us <> s0").select("uid", "us", "ue")


def later_runs(rows: DataFrame, min_words: int = 5) -> DataFrame:
    """(uid, s, e): maximal runs of lines (first and last position) that repeat what came before."""
    if min_words < 1:
        raise ValueError("a run has at least one word")
    units = materialise(line_units(rows), "lines")
    levels = suffix_ranks(units)
    copies = _short_copies(levels, min_words)
    if (deep := _deep_copies(levels, min_words)) is not None:
        copies = copies.unionByName(deep)
    own = Window.partitionBy("uid").orderBy("us", "ue")
    seen = F.max("ue").over(own.rowsBetween(Window.unboundedPreceding, -1))
    fresh = F.when(F.col("us") > F.coalesce(seen, F.lit(-2)) + 1, 1).otherwise(0)  # neighbours join, and blank lines between them
    islands = copies.withColumn("new", fresh).withColumn("run", F.sum("new").over(own)).groupBy("uid", "run").agg(F.min("us").alias("us"), F.max("ue").alias("ue"))
    place = levels[0].select("uid", "u", "pos")
    ends = islands.join(place.select("uid", F.col("u").alias("us"), F.col("pos").alias("s")), ["uid", "us"]).join(place.select("uid", F.col("u").alias("ue"), F.col("pos").alias("e")), ["uid", "ue"])
    out = materialise(ends.select("uid", "s", "e"), "runs")
    discard(units, *levels)
    return out


def dedupe(docs: DataFrame, min_words: int = 5) -> DataFrame:
    """``docs(doc_id, text, ...)`` with later copies of repeated line runs taken out of ``text``; adds lines, removed_lines and emptied."""
    carried = Carried(docs, "doc_id", "text", taken=RESULT)
    rows = materialise(carried.rows.withColumn("uid", F.monotonically_increasing_id()), "documents")
    runs = later_runs(rows.where("length(text) > 0").select("uid", "doc_id", F.col("text").cast("string").alias("text")), min_words)
    per = materialise(runs.groupBy("uid").agg(F.collect_list(F.struct("s", "e")).alias("runs")), "runs")
    split = F.split("text", "\n", -1)
    touched, clean = split_by(rows, per, "uid")
    left = F.expr("filter(all_lines, (x, i) -> not exists(runs, r -> i between r.s and r.e))")
    changed = (
        touched.join(per.hint("merge"), "uid", "left").withColumn("all_lines", split).withColumn("kept_lines", F.when(F.col("runs").isNull(), F.col("all_lines")).otherwise(left))
        .withColumns({"text": F.array_join("kept_lines", "\n"), "lines": F.size("all_lines"), "removed_lines": F.size("all_lines") - F.size("kept_lines")})
        .withColumn("emptied", (F.col("removed_lines") > 0) & ~F.exists("kept_lines", lambda x: F.trim(x) != ""))
        .withColumn("text", F.when(F.col("emptied"), "").otherwise(F.col("text")))
    )
    same = clean.withColumns({"lines": F.coalesce(F.size(split), F.lit(0)), "removed_lines": F.lit(0), "emptied": F.lit(False)})
    return changed.select(*carried.back(), *RESULT).unionByName(same.select(*carried.back(), *RESULT))


#: The same for DuckDB, on the text of the lines instead of names.
ORACLE = r"""
with raw as (select doc_id, text, string_split(text, chr(10)) as ls from documents),
units as (select doc_id, pos, trim(line) as line, len(regexp_extract_all(line, '\S+')) as w
          from (select doc_id, unnest(ls) as line, generate_subscripts(ls, 1) - 1 as pos from raw where length(text) > 0)
          where len(regexp_extract_all(line, '\S+')) > 0),
summed as (select *, row_number() over p as i, sum(w) over p as c, sum(w) over p - w as b from units window p as (partition by doc_id order by pos)),
lists as (select doc_id, list(line order by i) as all_lines, list(pos order by i) as all_pos from summed group by doc_id),
ahead as (select s.doc_id, s.i as i0, min(e.i) as i1 from summed s join summed e on s.doc_id = e.doc_id and e.i between s.i and s.i + 4 and e.c - s.b >= 5 group by all),
behind as (select e.doc_id, max(s.i) as i0, e.i as i1 from summed e join summed s on s.doc_id = e.doc_id and s.i between e.i - 4 and e.i and e.c - s.b >= 5 group by e.doc_id, e.i),
windows as (select doc_id, i0, i1, all_lines[i0:i1] as k from (select * from ahead union select * from behind) join lists using (doc_id)),
ranked as (select doc_id, i0, i1, row_number() over (partition by k order by doc_id, i0) as r from windows),
gone as (select distinct doc_id, unnest(range(i0, i1 + 1)) as i from ranked where r > 1),
spots as (select s.doc_id, s.i, s.pos, g.i is not null as out from summed s left join gone g on g.doc_id = s.doc_id and g.i = s.i),
dead as (select doc_id, unnest(range(pos, case when next_out then next_pos else pos + 1 end)) as pos
         from (select *, lead(out) over (partition by doc_id order by i) as next_out, lead(pos) over (partition by doc_id order by i) as next_pos from spots) where out),
parts as (select r.doc_id, line, pos from (select doc_id, unnest(ls) as line, generate_subscripts(ls, 1) - 1 as pos from raw) r anti join dead d on r.doc_id = d.doc_id and r.pos = d.pos),
kept as (select doc_id, string_agg(line, chr(10) order by pos) as t, count(*) as n, bool_or(trim(line) <> '') as wordy from parts group by doc_id)
select raw.doc_id, cast(coalesce(len(ls), 0) as int) as lines, cast(coalesce(len(ls), 0) - coalesce(n, 0) as int) as removed_lines,
       case when raw.text is null then null when len(ls) > coalesce(n, 0) and not coalesce(wordy, false) then '' else coalesce(t, '') end as text,
       coalesce(len(ls) > coalesce(n, 0) and not coalesce(wordy, false), false) as emptied
from raw left join kept using (doc_id)
"""
