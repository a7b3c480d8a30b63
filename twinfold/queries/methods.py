"""Methods, variants, baselines, measures and workloads: query and oracle side by side."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import biometrics as bio, detect as det, resolve as res, stats
from ..plans.storage import materialise
from ..sources import catalog, planted
from . import oracle as o

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _docs(spark, d, subject="source", want=catalog.DETECT) -> DataFrame:
    return materialise(catalog.sign(catalog.documents(spark, d, subject), want), "signed")


def _found(spark, d, subject="source", detectors=det.DETECTORS, **options) -> tuple[DataFrame, DataFrame]:
    """Signed documents and their sets, exact ones checked by their bytes."""
    s = _docs(spark, d, subject, detectors)
    return s, det.detect(s, detectors, contents=catalog.documents(spark, d, subject), **options)


def _planted(spark, d) -> DataFrame:
    return materialise(planted.signed(spark, d), "signed")


# ---- exact copies

for _algo in ("sha2", "md5"):
    query(f"digest_{_algo}", f"select doc_id as image_id, {'sha256' if _algo == 'sha2' else 'md5'}(text) as digest from documents")(
        lambda spark, d, a=_algo: det.with_digest(catalog.documents(spark, d), a).select("image_id", "digest")
    )


@query("digest_blake3")
def digest_blake3(spark, d):
    return det.with_digest(catalog.documents(spark, d), "blake3").select("image_id", "digest")


@query("exact_weak_digest", "select doc_id as image_id, concat('bytes:', first) as set_id from (select doc_id, arg_min(doc_id, concat(source, '/', lpad(cast(doc_id as varchar), 10, '0'))) over (partition by text) as first, count(*) over (partition by text) as n from documents) where n > 1")
def exact_weak_digest(spark, d):
    """Eight bits of a checksum collide all over; the byte check still gives the true sets."""
    return det.exact_sets(det.with_digest(catalog.documents(spark, d), "crc32", bits=8), max_rounds=500).select("image_id", "set_id")


@query("exact_candidates", "select doc_id as image_id, sha256(text) as digest, cast(octet_length(encode(text)) as int) as length from documents where sha256(text) in (select sha256(text) from documents group by 1 having count(*) > 1)")
def exact_candidates(spark, d):
    return det.exact_candidates(det.with_digest(catalog.documents(spark, d))).select("image_id", "digest", "length")


@query("exact_sets", ORACLES["exact_weak_digest"])
def exact_sets(spark, d):
    return det.exact_sets(det.with_digest(catalog.documents(spark, d))).select("image_id", "set_id")


@query("exact_by_content", "select doc_id as image_id, md5(text) as set_id from documents where text in (select text from documents group by text having count(*) > 1)")
def exact_by_content(spark, d):
    return det.by_content(catalog.documents(spark, d)).select("image_id", "set_id")


@query("keep_exact_intra", "select sha256(text) as digest, min(concat(source, '/', lpad(cast(doc_id as varchar), 10, '0'))) as kept_path, count(*) as copies from documents group by text, lang having count(*) > 1")
def keep_exact_intra(spark, d):
    """Exact copies by language (a single-subject labelling): the first path stays."""
    c = det.with_digest(catalog.documents(spark, d, "lang"))
    return c.groupBy("digest", "subject").agg(F.min("path").alias("kept_path"), F.count("*").alias("copies")).where("copies > 1").select("digest", "kept_path", "copies")


@query("keep_random", "select set_id, arg_min(image_id, (md5(concat('7:', path)), path)) as kept from (select concat('digest:', sha256(text)) as set_id, doc_id as image_id, concat(source, '/', lpad(cast(doc_id as varchar), 10, '0')) as path, count(*) over (partition by text) as n from documents) where n > 1 group by set_id")
def keep_random(spark, d):
    c = det.with_digest(catalog.documents(spark, d))
    return res.keep_random(det.digest_sets(c), c, seed=7)


# ---- hashes and near sets

_DOC = o.documents("source", features=False)
_DOCF = o.documents("source")


@query("dct_hash", o.with_(_DOC) + " select image_id, hi, lo, ahi, alo from signed")
def dct_hash(spark, d):
    return catalog.sign(catalog.documents(spark, d), ("dct",)).select("image_id", "hi", "lo", "ahi", "alo")


@query("segment_hash", o.with_(_DOC) + " select image_id, seg, aseg from signed")
def segment_hash(spark, d):
    """The crop-tolerant hash of texts: gradient hashes of their lines."""
    return catalog.sign(catalog.documents(spark, d), ("segment",)).select("image_id", "seg", "aseg")


@query("segment_hash_sets", o.with_(_DOC, o.sets()) + " select set_id, image_id, variant from sets where detector = 'segment'")
def segment_hash_sets(spark, d):
    s = _docs(spark, d, want=("segment",))
    return det.segment_sets(s).unionByName(det.segment_sets(s, "aligned")).select("set_id", "image_id", "variant")


@query("normalised_text", r"select doc_id as image_id, case when len(l) >= 5 then array_to_string(l, ' ') end as aligned from (select doc_id, list_filter(regexp_extract_all(lower(text), '[\p{L}\p{N}]+'), lambda w: length(w) > 1 and not regexp_matches(w, '[0-9]')) as l from documents)")
def normalised_text(spark, d):
    from ..functions import text as txt

    return catalog.documents(spark, d).select("image_id", txt.normalised(F.col("content")).alias("aligned"))


@query("page_main_text", r"select page_id as image_id, nullif(trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script\b.*?</script>|<style\b.*?</style>|<nav\b.*?</nav>|<header\b.*?</header>|<footer\b.*?</footer>|<aside\b.*?</aside>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '\s+', ' ', 'g')), '') as main_text from pages")
def page_main_text(spark, d):
    from ..functions import text as txt

    return catalog.pages(spark, d).select("image_id", txt.main_content(F.col("content")).alias("main_text"))


_G = rf"corpus as (select doc_id as image_id, text as content from documents), toks as (select image_id, {o.TOKENS} as l from corpus where content is not null), none_ as (select image_id, 0 as ln, l from toks where false)," + o._regions("g_", "toks", "none_", "g_out")


@query("gradient_hash", "with " + _G + " select image_id, coalesce(hi, 0) as hi, coalesce(lo, 0) as lo from g_parts left join g_grad using (image_id, ln)")
def gradient_hash(spark, d):
    """64 bits: each of 8 x 9 cells brighter than its left neighbour."""
    return catalog.gradient_hash(catalog.documents(spark, d))


@query("dct_hash_16")
def dct_hash_16(spark, d):
    """A longer hash: 16 x 16 low frequencies, 256 bits as eight words."""
    return catalog.long_hash(catalog.documents(spark, d), 16)


@query("dct_hash_sets", o.with_(_DOC, o.sets(digest=False, variants=("original",))) + " select set_id, image_id from sets")
def dct_hash_sets(spark, d):
    """Sets of equal frequency hashes and of equal region hashes of the originals."""
    return det.detect(_docs(spark, d, want=("dct", "segment")), ("dct", "segment"), ("original",)).select("set_id", "image_id")


@query("dct_hash_pairs_r6", o.with_(_DOC, "reps as (select hi, lo, min(image_id) as rep from signed group by hi, lo)") + " select a.rep as a, b.rep as b, cast(bit_count(xor(a.hi, b.hi)) + bit_count(xor(a.lo, b.lo)) as int) as distance from reps a join reps b on a.rep < b.rep where bit_count(xor(a.hi, b.hi)) + bit_count(xor(a.lo, b.lo)) <= 6")
def dct_hash_pairs_r6(spark, d):
    return det.hash_pairs(_docs(spark, d, want=("dct",)), 6)


@query("hash_bucket_histogram", o.with_(_DOC) + " select images, count(*) as hashes from (select count(*) as images from signed group by hi, lo) group by images")
def hash_bucket_histogram(spark, d):
    return det.hash_histogram(_docs(spark, d, want=("dct",)))


@query("detect_all", o.with_(_DOC, o.sets()) + " select set_id, image_id, detector, variant from sets")
def detect_all(spark, d):
    return _found(spark, d)[1]


@query("detect_variants", o.with_(_DOC, o.sets(digest=False)) + " select set_id, image_id, variant from sets")
def detect_variants(spark, d):
    return _found(spark, d, detectors=("dct", "segment"))[1].select("set_id", "image_id", "variant")


@query("within_subject_only", o.with_(_DOC, o.sets()) + " select concat(set_id, '|', subject) as set_id, image_id, detector, variant from (select s.*, subject, count(*) over (partition by set_id, subject) as n from sets s join signed using (image_id)) where n > 1")
def within_subject_only(spark, d):
    return _found(spark, d, within_subject_only=True)[1]


@query("detector_yield", o.with_(_DOC, o.sets()) + " select detector, variant, count(distinct image_id) as images, count(distinct set_id) as sets from sets group by detector, variant")
def detector_yield(spark, d):
    return stats.detector_yield(_found(spark, d)[1])


@query("variant_yield", o.with_(_DOC, o.sets(digest=False)) + " select count(*) filter (where o and not a) as original_only, count(*) filter (where a and not o) as aligned_only, count(*) filter (where a and o) as both from (select image_id, bool_or(variant = 'original') as o, bool_or(variant = 'aligned') as a from sets group by image_id)")
def variant_yield(spark, d):
    return stats.variant_yield(_found(spark, d, detectors=("dct", "segment"))[1])


@query("preprocess_failures", o.with_(_DOC, o.sets()) + " select dataset, count(*) filter (where ahi is null) as failures, count(*) filter (where ahi is null and image_id in (select image_id from sets where variant = 'original')) as duplicates from signed group by dataset")
def preprocess_failures(spark, d):
    return stats.preprocess_failures(*_found(spark, d))


@query("set_kind", o.with_(_DOC, o.sets()) + " select set_id, count(*) as images, count(distinct subject) as subjects, case when count(distinct subject) > 1 then 'inter' else 'intra' end as kind from sets join signed using (image_id) group by set_id")
def set_kind(spark, d):
    s, sets = _found(spark, d)
    return stats.classify(sets, s)


_CROSS = """corpus as (select 'documents' as dataset, doc_id as image_id, '' as path, '' as subject, text as content from documents union all select 'benchmark', 1000000000 + item_id, '', '', text from benchmark
union all select 'conversations', 2000000000 + conv_id * 1000 + turn, '', '', text from conversations union all select 'reposts', 3000000000 + doc_id, '', '', text || ' 7 x 9' from documents where doc_id % 20 = 0
union all select 'pages', 4000000000 + page_id, '', '', html from pages)"""


def _cross(variant: str) -> str:
    hi, lo = ("hi", "lo") if variant == "original" else ("ahi", "alo")
    return o.with_(_CROSS, o.text_signed(False)) + f" select concat('{variant}:', {hi}, ':', {lo}) as set_id, dataset, image_id from signed where ({hi}, {lo}) in (select ({hi}, {lo}) from signed where {hi} is not null group by {hi}, {lo} having count(distinct dataset) > 1)"


def _cross_corpus(spark, d) -> DataFrame:
    """Five collections in one; ``reposts`` are documents with tokens added that the normalised text does not have, so that the preprocessed pass must find them."""
    docs = catalog.documents(spark, d)
    reposts = docs.where("image_id % 20 = 0").withColumn("content", F.concat("content", F.lit(" 7 x 9")))
    parts = {"documents": docs, "benchmark": catalog.benchmark(spark, d), "conversations": catalog.conversations(spark, d), "reposts": reposts, "pages": catalog.pages(spark, d)}
    shifted = [p.withColumns({"dataset": F.lit(name), "image_id": F.col("image_id") + k * 1_000_000_000}) for k, (name, p) in enumerate(parts.items())]
    return reduce(DataFrame.unionByName, shifted)


for _v in ("original", "aligned"):
    query(f"cross_dataset_{_v}", _cross(_v))(lambda spark, d, v=_v: det.between(materialise(catalog.sign(_cross_corpus(spark, d), ("dct",)), "signed"), v))


@query("cross_dataset_passages", "select doc_id as image_id, item_id from documents d join benchmark b on contains(d.text, b.text)")
def cross_dataset_passages(spark, d):
    """Documents that contain a benchmark item."""
    return det.passages(catalog.documents(spark, d), catalog.benchmark(spark, d))


_MAIN = ORACLES["page_main_text"]


@query("cross_dataset_pages", f"with main as (select image_id, main_text from ({_MAIN}) where main_text is not null), quotes as (select image_id as item_id, substr(main_text, 21, 80) as quote from main where image_id % 10 = 0) select 'pages' as dataset, image_id, item_id from main join quotes on contains(main_text, quote) union all select 'documents', doc_id, item_id from documents join quotes on contains(text, quote)")
def cross_dataset_pages(spark, d):
    """Pages and documents against quotes of 80 characters from the main text of every tenth page: the pages quoted from, and whoever has the same passage."""
    from ..functions import text as txt

    main = materialise(catalog.pages(spark, d).select("image_id", txt.main_content(F.col("content")).alias("content")).where("content is not null"), "main")
    quotes = main.where("image_id % 10 = 0").select("image_id", F.substring("content", 21, 80).alias("content"))
    parts = {"pages": main, "documents": catalog.documents(spark, d)}
    return reduce(DataFrame.unionByName, [det.passages(x, quotes).select(F.lit(k).alias("dataset"), "image_id", "item_id") for k, x in parts.items()])


# ---- merging, correction, choice

@query("merged_sets", o.with_(_DOC, o.sets(), o.components()) + " select component, image_id from comps")
def merged_sets(spark, d):
    return res.merge(_found(spark, d)[1])


@query("merged_sets_local", o.with_(_DOC, o.sets(), o.components()) + " select component, image_id from comps")
def merged_sets_local(spark, d):
    return res.merge_local(_found(spark, d)[1])


_P = o.planted_signed()
_PSETS = (_P, o.sets(), o.components())


def _comps(spark, d):
    s = _planted(spark, d)
    sets = materialise(det.detect(s), "sets")
    return s, sets, materialise(res.merge(sets), "components")


for _rule in ("strict", "lenient", "split"):
    query({"strict": "fp_correction"}.get(_rule, f"fp_correction_{_rule}"), o.with_(*_PSETS, o.corrected(rule=_rule)) + " select component, image_id from solved")(
        lambda spark, d, r=_rule: (lambda t: res.correct(t[2], t[0], rule=r))(_comps(spark, d))
    )


@query("fp_missing_feature", o.with_(*_PSETS, o.corrected(missing="expel")) + " select component, image_id from solved")
def fp_missing_feature(spark, d):
    """The stricter option for pairs without a score."""
    s, _, c = _comps(spark, d)
    return res.correct(c, s, missing="expel")


@query("fp_released", o.with_(*_PSETS, o.corrected()) + " select image_id from comps where image_id not in (select image_id from solved)")
def fp_released(spark, d):
    s, _, c = _comps(spark, d)
    return c.join(res.correct(c, s), "image_id", "left_anti").select("image_id")


@query("fp_correction_documents", o.with_(_DOCF, o.sets(), o.components(), o.corrected()) + " select component, image_id from solved")
def fp_correction_documents(spark, d):
    s = _docs(spark, d, want=(*catalog.DETECT, "vec"))
    return res.correct(materialise(res.merge(det.detect(s, contents=catalog.documents(spark, d))), "components"), s)


_TAUS = [0.2, 0.3, 0.4, 0.5, 0.6, 0.8]


@query("threshold_sweep", o.with_(*_PSETS, f"""p as (select t.tau, x.image_id as a, y.image_id as b, case when p.vec is not null and q.vec is not null then {o.score('p.vec', 'q.vec')} end as score from comps x join comps y on x.component = y.component and x.image_id < y.image_id
    join signed p on p.image_id = x.image_id join signed q on q.image_id = y.image_id cross join (select unnest({_TAUS})::double as tau) t),
sides as (select tau, a as image_id, coalesce(score < floor(tau * 1048576 + 0.5), false) as f from p union all select tau, b, coalesce(score < floor(tau * 1048576 + 0.5), false) from p)""") + " select tau, count(*) filter (where f) as released, count(*) as images from (select tau, image_id, bool_or(f) as f from sides group by all) group by tau")
def threshold_sweep(spark, d):
    s, _, c = _comps(spark, d)
    return res.threshold_sweep(c, s, _TAUS)


@query("sample_sets", o.with_(_P, o.sets()) + " select set_id, image_id, detector, variant from sets where set_id in (select set_id from (select distinct set_id from sets) order by md5(concat('3:', set_id)), set_id limit 20)")
def sample_sets(spark, d):
    return res.sample_sets(det.detect(_planted(spark, d)), 20, seed=3)


_SOLVED = (*_PSETS, o.corrected())


@query("keep_best_quality", o.with_(*_SOLVED) + " select component, image_id as kept from (select component, image_id, row_number() over (partition by component order by case when q is null then '-infinity'::double else q end desc, path) as r from solved join signed using (image_id)) where r = 1")
def keep_best_quality(spark, d):
    s, _, c = _comps(spark, d)
    return res.keep_best(res.correct(c, s), s)


@query("nondup_reference", o.with_(_P, o.sets()) + " select image_id, subject from signed where image_id not in (select image_id from sets)")
def nondup_reference(spark, d):
    s = _planted(spark, d)
    return res.reference(s, det.detect(s)).select("image_id", "subject")


def _means(spark, d, strategy):
    s, sets, c = _comps(spark, d)
    solved = materialise(res.correct(c, s), "corrected")
    members = solved.join(s.select("image_id", "subject"), "image_id")
    inter = members.groupBy("component").agg(F.count_distinct("subject").alias("k")).where("k > 1").select("component")
    involved = members.join(inter, "component", "left_semi").select("component", "subject").distinct()
    kept = res.keep_best(solved, s).join(inter, "component", "left_semi")
    return s, kept, res.subject_scores(kept, involved, res.reference(s, sets), s, strategy)


_ALL_SCORES = (*_SOLVED, """ranked as (select component, image_id, subject, row_number() over (partition by component order by case when q is null then '-infinity'::double else q end desc, path) as r from solved join signed using (image_id)),
kept as (select component, image_id as kept, subject from ranked where r = 1), kinds as (select component, count(distinct subject) as k from ranked group by component),
refs as (select * from signed where image_id not in (select image_id from sets)), involved as (select distinct component, subject from ranked where component in (select component from kinds where k > 1))""")
_DOT = "cast(list_sum(list_transform(list_zip({0}, {1}), lambda p: p[1] * p[2])) as {2})"
_UNIT = "list_transform({0}, lambda x: cast(floor(cast(x as double) / sqrt(" + _DOT.format("{0}", "{0}", "double") + ") * 1048576 + 0.5) as bigint))"


@query("subject_scores_pairs", o.with_(*_ALL_SCORES) + f" select k.component, i.subject, round(cast(sum({o.score('o.vec', 'r.vec')}) as double) / count(*) / 1048576, 6) as mean, count(*) as n from kept k join involved i using (component) join signed o on o.image_id = k.kept and o.vec is not null join refs r on r.subject = i.subject and r.vec is not null group by all")
def subject_scores_pairs(spark, d):
    return _means(spark, d, "pairs")[2].select("component", "subject", F.round(F.col("mean") / 1048576, 6).alias("mean"), "n")


@query("subject_scores_centroid", o.with_(*_ALL_SCORES, f"""units as (select subject, unnest({_UNIT.format('vec')}) as x, generate_subscripts(vec, 1) as p from refs where vec is not null and subject in (select subject from involved)),
centre as (select subject, list(x order by p) as c, max(n) as n from (select subject, p, cast(sum(x) as bigint) as x, count(*) as n from units group by all) group by subject)""") + f" select k.component, i.subject, round({_DOT.format(_UNIT.format('o.vec'), 'c', 'double')} / 1048576 / n / 1048576, 6) as mean, n from kept k join involved i using (component) join signed o on o.image_id = k.kept and o.vec is not null join centre t on t.subject = i.subject")
def subject_scores_centroid(spark, d):
    return _means(spark, d, "centroid")[2].select("component", "subject", F.round(F.col("mean") / 1048576, 6).alias("mean"), "n")


@query("subject_candidates", o.with_(*_ALL_SCORES) + " select component, subject from involved i where exists (select 1 from refs r where r.subject = i.subject and r.vec is not null) and exists (select 1 from kept k join signed o on o.image_id = k.kept where k.component = i.component and o.vec is not null)")
def subject_candidates(spark, d):
    return _means(spark, d, "pairs")[2].select("component", "subject")


_ACTS = (_P, o.decided())


@query("subject_choice", o.with_(*_ACTS) + " select component, kept, case when reason = 'assigned' then best end as target, reason from placed")
def subject_choice(spark, d):
    s, sets, _ = _comps(spark, d)
    gone = res.actions(s).where("reason = 'exact_copy' and action = 'remove'").select("image_id")
    c = materialise(res.merge(det.repeated(sets.join(gone, "image_id", "left_anti"), "set_id")), "components")
    solved = materialise(res.correct(c, s), "corrected")
    members = solved.join(s.select("image_id", "subject"), "image_id")
    inter = members.groupBy("component").agg(F.count_distinct("subject").alias("k")).where("k > 1").select("component")
    kept = res.keep_best(solved, s).join(inter, "component", "left_semi")
    involved = members.join(inter, "component", "left_semi").select("component", "subject").distinct()
    return res.choose(kept, res.subject_scores(kept, involved, res.reference(s, sets), s), s)


@query("actions_all", o.with_(*_ACTS) + " select image_id, path, action, reason, from_subject, to_subject from acts")
def actions_all(spark, d):
    return res.actions(_planted(spark, d))


for _kind, _where in {"actions_intra": "reason in ('best_quality', 'exact_copy')", "actions_inter": "reason in ('assigned', 'thin_margin', 'below_floor', 'no_candidate', 'no_feature')", "subject_choice_nofeature": "reason = 'no_feature'"}.items():
    query(_kind, o.with_(*_ACTS) + f" select image_id, action, reason, to_subject from acts where {_where}")(lambda spark, d, w=_where: res.actions(_planted(spark, d)).where(w).select("image_id", "action", "reason", "to_subject"))


@query("actions_pairs", o.with_(*_ACTS) + " select image_id, action, reason, to_subject from acts")
def actions_pairs(spark, d):
    """Every pair of a kept and a reference image decides like the mean unit vectors."""
    return res.actions(_planted(spark, d), strategy="pairs").select("image_id", "action", "reason", "to_subject")


@query("actions_documents", o.with_(o.documents("mix"), o.decided()) + " select image_id, path, action, reason, from_subject, to_subject from acts")
def actions_documents(spark, d):
    return res.actions(_docs(spark, d, "mix", catalog.ALL), contents=catalog.documents(spark, d))


# ---- statistics

_T1 = """, flags as (select image_id, max((k = 1)::int) as intra, max((k > 1)::int) as inter from sets join (select set_id, count(distinct subject) as k from sets join signed using (image_id) group by set_id) using (set_id) group by image_id),
per as (select dataset, subject, count(*) as n, coalesce(sum(intra), 0) as a, coalesce(sum(inter), 0) as e, count(*) filter (where intra = 1 and inter = 1) as b from signed left join flags using (image_id) group by all)
select dataset, cast(sum(n) as bigint) as images, count(*) as subjects, cast(sum(a) as bigint) as intra, count(*) filter (where a > 0) as subjects_with_intra, cast(sum(e) as bigint) as inter, count(*) filter (where e > 0) as subjects_with_inter,
cast(sum(b) as bigint) as both, cast(sum(a) + sum(e) - sum(b) as bigint) as combined, round((sum(a) + sum(e) - sum(b))::double / sum(n), 6) as share from per group by dataset"""

for _s in ("source", "lang", "mix"):
    query(f"table1_{_s}", o.with_(o.documents(_s, False), o.sets()) + _T1)(lambda spark, d, s=_s: stats.overview(*_found(spark, d, s)))


@query("table1_planted", o.with_(_P, o.sets()) + _T1)
def table1_planted(spark, d):
    s = _planted(spark, d)
    return stats.overview(s, det.detect(s))


_PAGES = r"corpus as (select 'pages' as dataset, page_id as image_id, url as path, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as subject, html as content from pages)"


@query("table1_pages", o.with_(_PAGES, o.text_signed(False), o.sets()) + _T1)
def table1_pages(spark, d):
    """The control with nearly no copies."""
    c = catalog.pages(spark, d)
    s = materialise(catalog.sign(c, catalog.DETECT), "signed")
    return stats.overview(s, det.detect(s, contents=c))


@query("intra_inter_overlap", o.with_(_P, o.sets(), "k as (select set_id, count(distinct subject) as k from sets join signed using (image_id) group by set_id)") + " select image_id from sets join k using (set_id) where k = 1 intersect select image_id from sets join k using (set_id) where k > 1")
def intra_inter_overlap(spark, d):
    s = _planted(spark, d)
    sets = det.detect(s)
    kinds = sets.join(stats.classify(sets, s).select("set_id", "kind"), "set_id")
    return kinds.where("kind = 'intra'").select("image_id").intersect(kinds.where("kind = 'inter'").select("image_id"))


_T2 = " select count(*) filter (where action = 'remove') as removed, count(*) filter (where action = 'move') as moved, count(*) filter (where action = 'keep') as kept from acts"


@query("table2", o.with_(*_ACTS) + _T2)
def table2(spark, d):
    return stats.results(res.actions(_planted(spark, d)))


for _s in ("source", "lang", "mix"):
    query({"source": "table2_documents"}.get(_s, f"table2_{_s}"), o.with_(o.documents(_s), o.decided()) + _T2)(
        lambda spark, d, s=_s: stats.results(res.actions(_docs(spark, d, s, catalog.ALL), contents=catalog.documents(spark, d)))
    )


@query("table2_pages", o.with_(_PAGES, o.text_signed(), o.decided()) + _T2)
def table2_pages(spark, d):
    c = catalog.pages(spark, d)
    return stats.results(res.actions(materialise(catalog.sign(c), "signed"), contents=c))


@query("preprocess_failures_pages", o.with_(_PAGES, o.text_signed(False), o.sets()) + " select dataset, count(*) filter (where ahi is null) as failures, count(*) filter (where ahi is null and image_id in (select image_id from sets where variant = 'original')) as duplicates from signed group by dataset")
def preprocess_failures_pages(spark, d):
    c = catalog.pages(spark, d)
    s = materialise(catalog.sign(c, catalog.DETECT), "signed")
    return stats.preprocess_failures(s, det.detect(s, contents=c))


@query("preprocess_failures_planted", o.with_(_P, o.sets()) + " select dataset, count(*) filter (where ahi is null) as failures, count(*) filter (where ahi is null and image_id in (select image_id from sets where variant = 'original')) as duplicates from signed group by dataset")
def preprocess_failures_planted(spark, d):
    s = _planted(spark, d)
    return stats.preprocess_failures(s, det.detect(s))


@query("detector_yield_planted", o.with_(_P, o.sets()) + " select detector, variant, count(distinct image_id) as images, count(distinct set_id) as sets from sets group by detector, variant union all select 'both hashes', 'any', count(distinct image_id), count(distinct set_id) from sets where detector <> 'digest'")
def detector_yield_planted(spark, d):
    """Each detector alone, and both hashes together."""
    sets = materialise(det.detect(_planted(spark, d)), "sets")
    near = sets.where("detector <> 'digest'").agg(F.count_distinct("image_id").alias("images"), F.count_distinct("set_id").alias("sets"))
    return stats.detector_yield(sets).unionByName(near.select(F.lit("both hashes").alias("detector"), F.lit("any").alias("variant"), "images", "sets"))


_SHARES = (0.25, 0.5, 1.0)


@query("scale_behaviour", o.with_(_P, f"shares as (select unnest({list(_SHARES)})::double as share)", "part as (select s.*, share from signed s join shares on cast('0x' || substr(md5(s.path), 1, 6) as int) < share * 16777216)",
    "n as (select share, count(*) as images, count(distinct subject) as subjects from part group by share)",
    "k as (select share, cast(sum(c * (c - 1) // 2) as bigint) as all_pairs, cast(sum(case when c > 2 then c when c = 2 then 1 else 0 end) as bigint) as circular from (select share, subject, count(*) as c from part group by all) group by share)",
    "h as (select share, count(*) as sets, cast(sum(c) as bigint) as set_images from (select share, hi, count(*) as c from part group by share, hi having count(*) > 1) group by share)") + " select share, images, subjects, all_pairs, circular, sets, set_images from n join k using (share) join h using (share)")
def scale_behaviour(spark, d):
    """How counts grow on nested samples of a collection: images and circular pairs in proportion, all pairs faster."""
    s = _planted(spark, d).withColumn("u", F.conv(F.substring(F.md5("path"), 1, 6), 16, 10).cast("long"))
    part = materialise(s.select("image_id", "subject", "hi", "lo", "u", F.explode(F.array(*[F.lit(x) for x in _SHARES])).alias("share")).where(F.col("u") < F.col("share") * 16777216), "shares")
    n = part.groupBy("share").agg(F.count("*").alias("images"), F.count_distinct("subject").alias("subjects"))
    k = bio.mated_counts(part, ("share",)).select("share", "all_pairs", "circular")
    h = part.groupBy("share", "hi", "lo").agg(F.count("*").alias("c")).where("c > 1").groupBy("share").agg(F.count("*").alias("sets"), F.sum("c").alias("set_images"))
    return n.join(k, "share").join(h, "share")


@query("planted_pr", o.with_(_P, o.sets(), "f as (select distinct x.image_id as a, y.image_id as b from sets x join sets y on x.set_id = y.set_id and x.image_id < y.image_id)", "t as (select x.image_id as a, y.image_id as b from signed x join signed y on x.hi = y.hi and x.image_id < y.image_id where x.hi < 5000000)", "c as (select count(f.a) as found, count(t.a) as planted, count(*) filter (where f.a is not null and t.a is not null) as hits from f full join t on f.a = t.a and f.b = t.b)") + " select found, planted, hits, round(hits / found, 6) as precision, round(hits / planted, 6) as recall, round(2 * (hits / found) * (hits / planted) / (hits / found + hits / planted), 6) as f1 from c")
def planted_pr(spark, d):
    """Detected pairs against the planted ones (collisions planted on purpose are not true)."""
    s = _planted(spark, d)
    a, b = s.where("hi < 5000000").select("image_id", "hi").alias("a"), s.select("image_id", "hi").alias("b")
    truth = a.join(b, (F.col("a.hi") == F.col("b.hi")) & (F.col("a.image_id") < F.col("b.image_id"))).select(F.col("a.image_id").alias("a"), F.col("b.image_id").alias("b"))
    return stats.pair_quality(stats.set_pairs(det.detect(s)), truth)


@query("cost_pairs", o.with_(*_PSETS) + " select (select count(*) from signed) as digests, (select cast(sum(n * (n - 1) // 2) as bigint) from (select count(*) as n from signed group by subject)) as all_mated, (select cast(sum(case when n > 2 then n when n = 2 then 1 else 0 end) as bigint) from (select count(*) as n from signed group by subject)) as circular_mated, (select cast(sum(k * (k - 1) // 2) as bigint) from (select count(*) as k from comps group by component)) as correction_pairs, (select count(distinct image_id) from sets) as set_images")
def cost_pairs(spark, d):
    s, sets, c = _comps(spark, d)
    return stats.costs(s, sets, c)


# ---- variants and comparisons

_VAR = (*_ACTS, o.variants())


def _variants(signed: DataFrame, contents: DataFrame | None = None, quality: DataFrame | None = None) -> DataFrame:
    """The original collection, the one without any image of any set, and the one after the actions, as one table with ``variant``. ``quality(image_id, q)`` takes the place of the first provider; the actions keep the first."""
    acts = materialise(res.actions(signed, contents=contents), "actions")
    gone = materialise(det.detect(signed, contents=contents).select("image_id").distinct(), "in-sets")
    own = signed if quality is None else signed.drop("q").join(quality.hint("merge"), "image_id", "left")
    parts = {"original": own, "full": res.full_removal(own, gone), "preservative": res.preservative(own, acts)}
    return reduce(DataFrame.unionByName, [x.select(F.lit(v).alias("variant"), "image_id", "path", "subject", "ahi", "vec", "q") for v, x in parts.items()])


for _v in ("original", "full", "preservative"):
    query(f"variant_{_v}", o.with_(*_VAR) + f" select image_id, path, subject from variants where variant = '{_v}'")(lambda spark, d, v=_v: _variants(_planted(spark, d)).where(F.col("variant") == v).select("image_id", "path", "subject"))

_ORDERS = "corpus as (select o_custkey as subject, o_orderkey as image_id, lpad(cast(o_orderkey as varchar), 10, '0') as path from orders)"


def _orders(spark, d):
    t = catalog.table(spark, d, "orders")
    return t.select(F.col("o_custkey").alias("subject"), F.col("o_orderkey").alias("image_id"), catalog.padded("o_orderkey").alias("path"))


@query("mated_circular", "with " + _ORDERS + ", n as (select subject, image_id as a, lead(image_id) over w as nx, first_value(image_id) over w as f, count(*) over (partition by subject) as k from corpus window w as (partition by subject order by path)) select subject, a, coalesce(nx, f) as b from n where nx is not null or k > 2")
def mated_circular(spark, d):
    return bio.mated_circular(_orders(spark, d))


@query("mated_all", "select x.label as subject, x.vec_id as a, y.vec_id as b from embeddings x join embeddings y on x.label = y.label and x.vec_id < y.vec_id")
def mated_all(spark, d):
    e = catalog.table(spark, d, "embeddings").select(F.col("label").alias("subject"), F.col("vec_id").alias("image_id"), catalog.padded("vec_id").alias("path"))
    return bio.mated_all(e)


_COUNTS = "select cast(sum(case when n > 2 then n when n = 2 then 1 else 0 end) as bigint) as circular, cast(sum(n * (n - 1) // 2) as bigint) as all_pairs, count(*) filter (where n = 1) as single_subjects, count(*) filter (where n = 2) as two_subjects from (select count(*) as n from {0} group by {1})"


@query("mated_pair_counts", _COUNTS.format("orders", "o_custkey"))
def mated_pair_counts(spark, d):
    return bio.mated_counts(_orders(spark, d))


@query("mated_pair_counts_conversations", _COUNTS.format("conversations", "conv_id"))
def mated_pair_counts_conversations(spark, d):
    return bio.mated_counts(catalog.conversations(spark, d))


_CMP = (*_VAR, o.comparisons())


@query("nonmated_pairs", o.with_(*_CMP) + " select a, b from others where variant = 'original'")
def nonmated_pairs(spark, d):
    able = _planted(spark, d).where("ahi is not null").select("image_id", "path", "subject")
    return bio.nonmated(able, int(bio.mated_counts(able).first()["circular"]))


@query("pair_scores", o.with_(*_CMP) + " select a, b, mated, score, pair_q from scored where variant = 'original'")
def pair_scores(spark, d):
    return bio.comparisons(_planted(spark, d)).select("a", "b", "mated", "score", "pair_q")


def _scored(spark, d) -> DataFrame:
    return materialise(bio.comparisons(_variants(_planted(spark, d))), "scored")


_RATES = (*_CMP, o.rates())


@query("error_rates", o.with_(*_RATES) + " select variant, threshold, round(fnmr, 6) as fnmr, round(fmr, 6) as fmr from curve")
def error_rates(spark, d):
    return bio.rates(_scored(spark, d), "variant").select("variant", "threshold", F.round("fnmr", 6).alias("fnmr"), F.round("fmr", 6).alias("fmr"))


@query("eer", o.with_(*_RATES) + " select variant, round(eer, 6) as eer, threshold from (select variant, (fnmr + fmr) / 2 as eer, threshold, row_number() over (partition by variant order by abs(fnmr - fmr), threshold) as r from curve) where r = 1")
def eer(spark, d):
    return bio.eer(bio.rates(_scored(spark, d), "variant"), "variant")


@query("fnmr_at_fmr", o.with_(*_RATES) + " select variant, target, round(fnmr, 6) as fnmr, round(fmr, 6) as fmr from (select variant, target, fnmr, fmr, row_number() over (partition by variant, target order by fmr desc, fnmr) as r from curve cross join (select unnest([0.001, 0.01])::double as target) t where fmr <= target) where r = 1")
def fnmr_at_fmr(spark, d):
    return bio.fnmr_at(bio.rates(_scored(spark, d), "variant"), [0.001, 0.01], "variant")


_SOLO = "variants as (select 'original' as variant, image_id, path, subject, ahi, vec, q from signed)"


def _edc_sql(error: str, tail: str, start: float = 0.05, signed: str | None = None, variants: str | None = None) -> str:
    rated = _RATES if variants is None else (signed or _P, variants, o.comparisons(), o.rates())
    return o.with_(*rated, o.discard(error, start)) + tail


for _e in ("fnmr", "fmr"):
    query(f"edc_{_e}", _edc_sql(_e, " select round(fraction, 6) as fraction, round(error, 6) as error from edc where variant = 'original'"))(
        lambda spark, d, e=_e: bio.edc(materialise(bio.comparisons(_planted(spark, d)), "scored"), e).select(F.round("fraction", 6).alias("fraction"), F.round("error", 6).alias("error"))
    )
    query(f"edc_pauc_{_e}", _edc_sql(_e, " , s as (select variant, fraction, error, least(coalesce(lead(fraction) over (partition by variant order by fraction), 1), 0.2) as e from edc) select variant, round(sum(floor((e - fraction) * error * 1e12 + 0.5))::double / 1e12, 6) as pauc from s where fraction < 0.2 group by variant"))(
        lambda spark, d, e=_e: bio.pauc(bio.edc(_scored(spark, d), e, by=("variant",)), by=("variant",))
    )


_STARTS = (0.02, 0.05, 0.1)


@query("edc_start", " union all ".join(f"(select {x}::double as start, * from ({_edc_sql('fnmr', ' select round(fraction, 6) as fraction, round(error, 6) as error from edc', start=x, variants=_SOLO)}))" for x in _STARTS))
def edc_start(spark, d):
    """The discard curve from several starting errors."""
    scored = materialise(bio.comparisons(_planted(spark, d)), "scored")
    curve = materialise(bio.rates(scored), "rates")
    parts = [bio.edc(scored, "fnmr", x, curve=curve).select(F.lit(x).alias("start"), F.round("fraction", 6).alias("fraction"), F.round("error", 6).alias("error")) for x in _STARTS]
    return reduce(DataFrame.unionByName, parts)


# Experiments: every measure of every variant, on a collection under a quality provider, with its change against the original.

_MEASURED = (*o.measures(), "changed as (select m.variant, m.measure, m.value, round(m.value - b.value, 6) as change from measured m join measured b on b.measure = m.measure and b.variant = 'original')")
_CHANGED = " select variant, measure, value, change from changed"
_LABEL_Q = "label_q as (select doc_id as image_id, cast(max(quality - toxic) as double) as q2 from labels group by doc_id)"


def _requalified(signed_sql: str, q: str, more: str = "", join: str = "") -> str:
    """The CTEs of ``signed`` with another quality provider."""
    return signed_sql.replace("signed as (select", "signed_1 as (select", 1) + f"{', ' + more if more else ''}, signed as (select signed_1.* exclude (q), {q} as q from signed_1 {join})"


def _experiment(signed: DataFrame, contents: DataFrame | None = None, quality: DataFrame | None = None) -> DataFrame:
    """``quality(image_id, q)`` takes the place of the first provider in the curves; the actions keep the first."""
    v = _variants(signed, contents, quality)
    return bio.changes(materialise(bio.measures(materialise(bio.comparisons(v), "scored"), ("variant",)), "measures"))


#: The second quality provider on the planted collection: many ties, every sixth image without a score.
_Q2 = "case when image_id % 6 <> 0 then cast((image_id * 7) % 5 as double) end"


def _second(variants: str, q: str, join: str = "") -> str:
    """The variants with another quality in the curves."""
    return variants.replace("variants as (", "variants_1 as (") + f", variants as (select v.* exclude (q), {q} as q from variants_1 v {join})"


@query("experiment_planted", o.with_(*_VAR, o.comparisons(), o.rates(), *_MEASURED) + _CHANGED)
def experiment_planted(spark, d):
    return _experiment(_planted(spark, d))


@query("experiment_planted_second_quality", o.with_(*_ACTS, _second(o.variants(), _Q2), o.comparisons(), o.rates(), *_MEASURED) + _CHANGED)
def experiment_planted_second_quality(spark, d):
    s = _planted(spark, d)
    return _experiment(s, quality=s.select("image_id", F.expr(_Q2).alias("q")))


_DOCS_DECIDED = (o.documents("mix"), o.decided())


@query("experiment_documents", o.with_(*_DOCS_DECIDED, o.variants(), o.comparisons(), o.rates(), *_MEASURED) + _CHANGED)
def experiment_documents(spark, d):
    """Shingle features say little about the labels of documents: near chance, whatever is removed."""
    return _experiment(_docs(spark, d, "mix", catalog.ALL), catalog.documents(spark, d))


@query("experiment_documents_second_quality", o.with_(*_DOCS_DECIDED, _LABEL_Q, _second(o.variants(), "q2", "left join label_q using (image_id)"), o.comparisons(), o.rates(), *_MEASURED) + _CHANGED)
def experiment_documents_second_quality(spark, d):
    """The same under the labels' quality."""
    quality = catalog.table(spark, d, "labels").groupBy(F.col("doc_id").alias("image_id")).agg(F.max(F.col("quality") - F.col("toxic")).cast("double").alias("q"))
    return _experiment(_docs(spark, d, "mix", catalog.ALL), catalog.documents(spark, d), quality)


@query("variant_deltas", o.with_(*_RATES, "x as (select variant, round((fnmr + fmr) / 2, 6) as eer, row_number() over (partition by variant order by abs(fnmr - fmr), threshold) as r from curve)") + " select variant, round(eer - (select eer from x where variant = 'original' and r = 1), 6) as change from x where r = 1 and variant <> 'original'")
def variant_deltas(spark, d):
    """Change of the equal error rate against the original."""
    e = bio.eer(bio.rates(_scored(spark, d), "variant"), "variant").select("variant", F.col("eer").alias("value"))
    return bio.changes(materialise(e, "eer")).where("variant <> 'original'").select("variant", "change")


_QL = "select c.image_id, 'text' as provider, q from signed c union all select doc_id, 'label', cast(max(quality - toxic) as double) from labels group by doc_id"


@query("quality_two_providers", o.with_(_DOC) + " " + _QL)
def quality_two_providers(spark, d):
    s = catalog.documents(spark, d).select("image_id", F.lit("text").alias("provider"), catalog.text_quality(F.col("content")).alias("q"))
    l = catalog.table(spark, d, "labels").groupBy(F.col("doc_id").alias("image_id")).agg(F.max(F.col("quality") - F.col("toxic")).cast("double").alias("q")).withColumn("provider", F.lit("label"))
    return s.unionByName(l)


# ---- further variants and workloads

@query("actions_exact_inter", o.with_(_P, o.decided(variants=())) + " select image_id, action, reason, to_subject from acts")
def actions_exact_inter(spark, d):
    """Byte copies alone: those across subjects go through the choice of the subject as well."""
    return res.actions(_planted(spark, d), detectors=("digest",)).select("image_id", "action", "reason", "to_subject")


@query("subject_choice_single", o.with_(*_ALL_SCORES, f"m as (select k.component, count(distinct i.subject) as n from kept k join involved i using (component) join signed x on x.image_id = k.kept and x.vec is not null join refs r on r.subject = i.subject and r.vec is not null group by k.component)") + " select component from m where n = 1")
def subject_choice_single(spark, d):
    """Sets with one candidate subject left: the margin has no second best and does not apply."""
    return _means(spark, d, "pairs")[2].groupBy("component").agg(F.count("*").alias("n")).where("n = 1").select("component")


@query("near_components_r6", o.with_(_DOC, """reps as (select hi, lo, min(image_id) as rep from signed group by hi, lo),
b as (select a.rep as u, b.rep as v from reps a join reps b on a.rep <> b.rep and bit_count(xor(a.hi, b.hi)) + bit_count(xor(a.lo, b.lo)) <= 6),
r as (select rep as a, rep as b from reps where rep in (select u from b) union select r.a, b.v from r join b on b.u = r.b),
c as (select a as rep, min(b) as component from r group by a)""") + " select coalesce(component, rep) as component, image_id from signed join reps using (hi, lo) left join c using (rep) where component is not null or (hi, lo) in (select (hi, lo) from signed group by hi, lo having count(*) > 1)")
def near_components_r6(spark, d):
    """The radius extension: components of equal hashes and of hashes within six bits."""
    sets = det.detect(_docs(spark, d, want=("dct",)), ("dct",), ("original",), radius=6)
    return sets.select(F.substring_index("set_id", ":", -1).cast("long").alias("component"), "image_id")


_EER = " select round((fnmr + fmr) / 2, 6) as eer, threshold from (select *, row_number() over (order by abs(fnmr - fmr), threshold) as r from curve) where r = 1"


@query("eer_documents", o.with_(o.documents("mix"), _SOLO, o.comparisons(), o.rates()) + _EER)
def eer_documents(spark, d):
    """Shingle features say little about the labels of documents: near chance."""
    return bio.eer(bio.rates(bio.comparisons(_docs(spark, d, "mix", catalog.ALL))))


_RAW = "signed as (select vec_id as image_id, cast(label as varchar) as subject, concat(label, '/', lpad(cast(vec_id as varchar), 10, '0')) as path, 1::bigint as ahi, list_transform(embedding, lambda x: cast(floor(cast(x as double) * 32768 + 0.5) as bigint)) as vec, cast(vec_id % 7 as double) as q from embeddings)"


@query("eer_raw_vectors", o.with_(_RAW, _SOLO, o.comparisons(), o.rates()) + _EER)
def eer_raw_vectors(spark, d):
    """The given vectors under their labels: chance level."""
    return bio.eer(bio.rates(bio.comparisons(_raw_vectors(spark, d))))


def _raw_vectors(spark, d) -> DataFrame:
    e = catalog.table(spark, d, "embeddings")
    vec = F.transform("embedding", lambda x: F.floor(x.cast("double") * 32768 + 0.5).cast("long"))
    path = F.concat(F.col("label").cast("string"), F.lit("/"), catalog.padded("vec_id"))
    return e.select(F.col("vec_id").alias("image_id"), F.col("label").cast("string").alias("subject"), path.alias("path"), F.lit(1).cast("long").alias("ahi"), vec.alias("vec"), (F.col("vec_id") % 7).cast("double").alias("q"))


_Q2_SIGNED = o.planted_signed().replace("signed as (select 'planted'", "signed_1 as (select 'planted'") + f", signed as (select * exclude (q), {_Q2} as q from signed_1)"
for _e in ("fnmr", "fmr"):
    _tail = " , s as (select variant, fraction, error, least(coalesce(lead(fraction) over (partition by variant order by fraction), 1), 0.2) as e from edc) select round(sum(floor((e - fraction) * error * 1e12 + 0.5))::double / 1e12, 6) as pauc from s where fraction < 0.2"
    query(f"edc_pauc_{_e}_second_quality", _edc_sql(_e, _tail, signed=_Q2_SIGNED, variants=_SOLO))(
        lambda spark, d, e=_e: bio.pauc(bio.edc(materialise(bio.comparisons(planted.signed(spark, d).withColumn("q", F.expr(_Q2))), "scored"), e))
    )


# ---- raw vectors: a control without copies

@query("experiment_raw_vectors", o.with_(_RAW, _SOLO, o.comparisons(), o.rates(), *o.measures()) + " select measure, value from measured")
def experiment_raw_vectors(spark, d):
    return bio.measures(materialise(bio.comparisons(_raw_vectors(spark, d)), "scored"), ())
