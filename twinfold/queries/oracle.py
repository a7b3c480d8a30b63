"""Common table expressions for DuckDB: the same definitions, relational and literal."""

from __future__ import annotations

from ..functions.arithmetic import BASIS, LUMINANCE, SCALE
from ..sources import planted

SUBJECT = {"source": "source", "lang": "lang", "mix": "concat(lang, '-', doc_id % 3)"}
TOKENS = r"regexp_extract_all(lower(content), '[\p{L}\p{N}]+')"


def _halves(prefix: str, words: str, out: str) -> str:
    """CTEs for the hash halves of ``words(image_id, w)`` as ``out(image_id, hi, lo)``; images without a word have no cells and get 0 later."""
    basis = ", ".join(f"({u}, {x}, {BASIS[u][x]})" for u in range(8) for x in range(32))
    light = "[" + ", ".join(map(str, LUMINANCE)) + "]"
    return f"""
{prefix}cells as (select image_id, cell // 32 as x, cell % 32 as y, {light}[least(count(*), 255) + 1] as p
                  from (select image_id, cast('0x' || substr(md5(w), 1, 3) as int) % 1024 as cell from {words}) group by image_id, cell),
{prefix}basis as (select * from (values {basis}) t(u, x, t)),
{prefix}rows as (select image_id, b.u, y, sum(t * p) as r from {prefix}cells c join {prefix}basis b on b.x = c.x group by image_id, b.u, y),
{prefix}coef as (select image_id, r.u * 8 + b.u as k, cast(sum(t * r.r) as bigint) as c from {prefix}rows r join {prefix}basis b on b.x = r.y group by image_id, r.u * 8 + b.u),
{prefix}mid as (select image_id, list_sort(list(c))[32] + list_sort(list(c))[33] as m from {prefix}coef group by image_id),
{out} as (select image_id, cast(sum(case when k < 32 and 2 * c > m then 1::bigint << (31 - k) else 0 end) as bigint) as hi,
                 cast(sum(case when k >= 32 and 2 * c > m then 1::bigint << (63 - k) else 0 end) as bigint) as lo from {prefix}coef join {prefix}mid using (image_id) group by image_id)"""


def _regions(prefix: str, tokens: str, lines: str, out: str) -> str:
    """CTEs for ``out(image_id, seg)``: gradient hashes of the lines of at least five tokens, else of the whole text, as one checksum."""
    return f"""
{prefix}large as (select image_id, ln, l from {lines} where len(l) >= 5),
{prefix}parts as (select * from {prefix}large union all select image_id, 0 as ln, l from {tokens} where image_id not in (select image_id from {prefix}large)),
{prefix}counts as (select image_id, ln, cell, count(*) as n from (select image_id, ln, cast('0x' || substr(md5(w), 1, 3) as int) % 72 as cell from (select image_id, ln, unnest(l) as w from {prefix}parts)) group by all),
{prefix}bits as (select a.image_id, a.ln, a.cell // 9 * 8 + a.cell % 9 - 1 as k from {prefix}counts a left join {prefix}counts b on b.image_id = a.image_id and b.ln = a.ln and b.cell = a.cell - 1 where a.cell % 9 > 0 and a.n > coalesce(b.n, 0)),
{prefix}grad as (select image_id, ln, cast(sum(case when k < 32 then 1::bigint << (31 - k) else 0 end) as bigint) as hi, cast(sum(case when k >= 32 then 1::bigint << (63 - k) else 0 end) as bigint) as lo from {prefix}bits group by all),
{out} as (select image_id, md5(string_agg(concat(coalesce(hi, 0), ':', coalesce(lo, 0)), '-' order by ln)) as seg from {prefix}parts left join {prefix}grad using (image_id, ln) group by image_id)"""


def documents(subject: str = "source", features: bool = True) -> str:
    """``signed`` for ``documents``."""
    corpus = f"""
corpus as (select 'documents-{subject}' as dataset, doc_id as image_id, concat(source, '/', lpad(cast(doc_id as varchar), 10, '0')) as path, {SUBJECT[subject]} as subject, text as content from documents)"""
    return corpus + "," + text_signed(features)


def text_signed(features: bool = True) -> str:
    vec = """
runs as (select image_id, array_to_string(l[i + 1:i + 3], ' ') as r from (select image_id, l, unnest(range(greatest(1, len(l) - 2))) as i from toks where len(l) > 0)),
sums as (select image_id, h % 64 as b, sum(case when (h >> 6) & 1 = 1 then -1 else 1 end) as x from (select image_id, cast('0x' || substr(md5(r), 1, 4) as int) as h from runs) group by image_id, h % 64),
vecs as (select i.image_id, list(cast(coalesce(x, 0) as bigint) order by g.b) as vec from (select distinct image_id from runs) i cross join (select unnest(range(64)) as b) g
         left join sums s on s.image_id = i.image_id and s.b = g.b group by i.image_id)"""
    return rf"""
toks as (select image_id, {TOKENS} as l from corpus where content is not null),
kept_toks as (select image_id, list_filter(l, lambda w: length(w) > 1 and not regexp_matches(w, '[0-9]')) as l from toks),
line_toks as (select image_id, ln, {TOKENS} as l from (select image_id, unnest(string_split(content, chr(10))) as content, generate_subscripts(string_split(content, chr(10)), 1) as ln from corpus where content is not null)),
kept_line_toks as (select image_id, ln, list_filter(l, lambda w: length(w) > 1 and not regexp_matches(w, '[0-9]')) as l from line_toks),
good_toks as (select * from kept_toks where len(l) >= 5),
words as (select image_id, unnest(l) as w from toks),
awords as (select image_id, unnest(l) as w from kept_toks where len(l) >= 5),
{_halves('o_', 'words', 'hash_o')},
{_halves('a_', 'awords', 'hash_a')},
{_regions('ro_', 'toks', 'line_toks', 'region_o')},
{_regions('ra_', 'good_toks', '(select * from kept_line_toks where image_id in (select image_id from good_toks))', 'region_a')},
{vec if features else "vecs as (select image_id, cast(null as bigint[]) as vec from corpus)"},
signed as (select c.dataset, c.image_id, c.path, c.subject, c.content, cast(octet_length(encode(c.content)) as bigint) as length, sha256(c.content) as digest,
                  coalesce(o.hi, 0) as hi, coalesce(o.lo, 0) as lo, case when len(k.l) >= 5 then coalesce(a.hi, 0) end as ahi, case when len(k.l) >= 5 then coalesce(a.lo, 0) end as alo, ro.seg, ra.seg as aseg, v.vec,
                  case when len(t.l) >= 5 then cast(floor(len(list_distinct(t.l)) * 1000 / len(t.l)) + least(length(c.content), 1000) as double) end as q
           from corpus c join toks t using (image_id) join kept_toks k using (image_id) left join hash_o o using (image_id) left join hash_a a using (image_id) left join vecs v using (image_id)
                left join region_o ro using (image_id) left join region_a ra using (image_id))"""


def planted_signed() -> str:
    return planted.sql(planted.DUCKDB)


def score(a: str, b: str) -> str:
    dot = "cast(list_sum(list_transform(list_zip({0}, {1}), lambda p: p[1] * p[2])) as double)"
    return f"cast(floor({dot.format(a, b)} / (sqrt({dot.format(a, a)}) * sqrt({dot.format(b, b)})) * {SCALE} + 0.5) as bigint)"


def sets(rows: str = "signed", out: str = "sets", digest: bool = True, variants=("original", "aligned"), segment: bool = True) -> str:
    parts = []
    if digest:
        parts.append(f"select 'digest:' || digest as set_id, image_id, 'digest' as detector, 'original' as variant from {rows} where digest in (select digest from {rows} group by digest having count(*) > 1)")
    for v, (hi, lo) in {"original": ("hi", "lo"), "aligned": ("ahi", "alo")}.items():
        if v in variants:
            parts.append(f"select concat('dct:{v}:', {hi}, ':', {lo}), image_id, 'dct', '{v}' from {rows} where ({hi}, {lo}) in (select ({hi}, {lo}) from {rows} where {hi} is not null group by {hi}, {lo} having count(*) > 1)")
            if segment:
                c = "seg" if v == "original" else "aseg"
                parts.append(f"select concat('segment:{v}:', {c}), image_id, 'segment', '{v}' from {rows} where {c} in (select {c} from {rows} where {c} is not null group by {c} having count(*) > 1)")
    return f"{out} as ({' union all '.join(parts)})" if digest else f"{out}(set_id, image_id, detector, variant) as ({' union all '.join(parts)})"


def components(source: str = "sets", out: str = "comps") -> str:
    """Transitive closure; for the small oracle scale only."""
    return f"""
{out}_star as (select distinct image_id as u, first as v from (select image_id, min(image_id) over (partition by set_id) as first from {source}) where image_id <> first),
{out}_both as (select u, v from {out}_star union select v, u from {out}_star),
{out}_reach as (select u as a, u as b from {out}_both union select r.a, e.v from {out}_reach r join {out}_both e on e.u = r.b),
{out} as (select min(b) as component, a as image_id from {out}_reach group by a)"""


def corrected(source: str = "comps", out: str = "solved", rule: str = "strict", tau: float = 0.4, missing: str = "keep") -> str:
    t = int(tau * SCALE + 0.5)
    fails = f"coalesce(score < {t}, {'true' if missing == 'expel' else 'false'})"
    pairs = f"""
{out}_pairs as (select component, a, b, {fails} as fails from (select x.component, x.image_id as a, y.image_id as b, case when p.vec is not null and q.vec is not null then {score('p.vec', 'q.vec')} end as score
     from {source} x join {source} y on x.component = y.component and x.image_id < y.image_id join signed p on p.image_id = x.image_id join signed q on q.image_id = y.image_id))"""
    if rule == "split":
        return pairs + f""",
{out}_both as (select a as u, b as v from {out}_pairs where not fails union select b, a from {out}_pairs where not fails),
{out}_reach as (select u as a, u as b from {out}_both union select r.a, e.v from {out}_reach r join {out}_both e on e.u = r.b),
{out} as (select min(b) as component, a as image_id from {out}_reach group by a)"""
    agg = "bool_or" if rule == "strict" else "bool_and"
    return pairs + f""",
{out}_gone as (select image_id from (select a as image_id, fails from {out}_pairs union all select b, fails from {out}_pairs) group by image_id having {agg}(fails)),
{out}_left as (select component, image_id from {source} where image_id not in (select image_id from {out}_gone)),
{out} as (select component, image_id from {out}_left where component in (select component from {out}_left group by component having count(*) > 1))"""


def decided(floor: float = 0.4, margin: float = 0.2, variants=("original", "aligned")) -> str:
    """From ``signed`` to ``acts``: exact single-subject copies first, then near sets (none without ``variants``)."""
    f, m = int(floor * SCALE + 0.5), int(margin * SCALE + 0.5)
    return f"""
{sets('signed', 'sets', variants=variants)},
exact_one as (select s.set_id, min(path) as first from sets s join signed using (image_id) where detector = 'digest' group by s.set_id having count(distinct subject) = 1),
exact_judged as (select s.image_id, g.path = e.first as kept from sets s join exact_one e using (set_id) join signed g on g.image_id = s.image_id where s.detector = 'digest'),
left_rows as (select * from signed where image_id not in (select image_id from exact_judged where not kept)),
{sets('left_rows', 'near_sets', variants=variants)},
{components('near_sets', 'comps')},
{corrected('comps', 'solved')},
ranked as (select component, image_id, subject, row_number() over (partition by component order by case when q is null or isnan(q) then '-infinity'::double else q end desc, path) as r from solved join signed using (image_id)),
kept as (select component, image_id as kept, subject from ranked where r = 1),
kinds as (select component, count(distinct subject) as k from ranked group by component),
refs as (select * from signed where image_id not in (select image_id from sets)),
involved as (select distinct component, subject from ranked where component in (select component from kinds where k > 1)),
means as (select k.component, k.kept, i.subject, cast(sum({score('o.vec', 'r.vec')}) as double) / count(*) as mean, count(*) as n
          from kept k join involved i using (component) join signed o on o.image_id = k.kept and o.vec is not null join refs r on r.subject = i.subject and r.vec is not null group by all),
best as (select component, subject as best, mean as top, lead(mean) over w as next, row_number() over w as r from means window w as (partition by component order by mean desc, subject)),
placed as (select k.component, k.kept, k.subject, b.best, case when o.vec is null then 'no_feature' when b.best is null then 'no_candidate' when b.top < {f} then 'below_floor'
                  when not coalesce(b.top - b.next >= {m}, true) then 'thin_margin' else 'assigned' end as reason
           from kept k join kinds using (component) join signed o on o.image_id = k.kept left join (select * from best where r = 1) b using (component) where k > 1),
second as (select image_id, 'remove' as action, 'lower_quality' as reason, cast(null as varchar) as to_subject from ranked where r > 1
           union all select kept, 'keep', 'best_quality', cast(null as varchar) from kept join kinds using (component) where k = 1
           union all select kept, case when reason <> 'assigned' then 'remove' when best <> subject then 'move' else 'keep' end, reason, case when reason = 'assigned' then best end from placed),
acts as (select x.image_id, path, action, reason, subject as from_subject, to_subject from (
           select * from second union all select image_id, case when kept then 'keep' else 'remove' end, 'exact_copy', cast(null as varchar) from exact_judged where image_id not in (select image_id from second)) x
         join signed using (image_id))"""


def variants() -> str:
    """``variants(variant, ...)``: original, full removal and preservative."""
    return """
final_rows as (select s.* exclude (subject), coalesce(m.to_subject, s.subject) as subject from signed s left join (select image_id, to_subject from acts where action = 'move') m using (image_id)
               where s.image_id not in (select image_id from acts where action = 'remove')),
variants as (select 'original' as variant, image_id, path, subject, ahi, vec, q from signed union all select 'full', image_id, path, subject, ahi, vec, q from signed where image_id not in (select image_id from sets)
             union all select 'preservative', image_id, path, subject, ahi, vec, q from final_rows)"""


def comparisons(seed: int = 1, over: int = 4) -> str:
    """``scored(variant, a, b, mated, score, pair_q)`` for each variant."""
    draw = "cast('0x' || substr(md5(concat('{0}:{1}:', i)), 1, 12) as bigint) % n"
    return f"""
able as (select *, row_number() over (partition by variant order by path) - 1 as idx, count(*) over (partition by variant) as n from variants where ahi is not null),
nexts as (select variant, subject, image_id as a, lead(image_id) over w as nx, first_value(image_id) over w as fst, count(*) over (partition by variant, subject) as k from able window w as (partition by variant, subject order by path)),
mated as (select variant, a, coalesce(nx, case when k > 2 then fst end) as b from nexts where nx is not null or k > 2),
wanted as (select variant, count(*) as c from mated group by variant),
draws as (select w.variant, i, c, {draw.format(seed, 'a')} as x, {draw.format(seed, 'b')} as y from (select variant, c, unnest(range({over} * c)) as i from wanted) w join (select distinct variant, n from able) using (variant)),
hits as (select d.variant, least(p.image_id, q.image_id) as a, greatest(p.image_id, q.image_id) as b, c, min(i) as i from draws d join able p on p.variant = d.variant and p.idx = d.x join able q on q.variant = d.variant and q.idx = d.y
         where p.subject <> q.subject group by all),
others as (select variant, a, b from (select *, row_number() over (partition by variant order by i) as r from hits) where r <= c),
scored as (select z.variant, z.a, z.b, mated, {score('p.vec', 'q.vec')} as score, case when p.q is null or q.q is null then '-infinity'::double else least(p.q, q.q) end as pair_q
           from (select variant, a, b, true as mated from mated union all select variant, a, b, false from others) z
           join able p on p.variant = z.variant and p.image_id = z.a join able q on q.variant = z.variant and q.image_id = z.b where p.vec is not null and q.vec is not null)"""


def rates() -> str:
    return """
bins as (select variant, score as threshold, count(*) filter (where mated) as m, count(*) filter (where not mated) as n from scored group by variant, score),
curve as (select variant, threshold, coalesce(sum(m) over p, 0)::double / sum(m) over (partition by variant) as fnmr,
                 (sum(n) over (partition by variant) - coalesce(sum(n) over p, 0))::double / sum(n) over (partition by variant) as fmr
          from bins window p as (partition by variant order by threshold rows between unbounded preceding and 1 preceding))"""


def discard(error: str, start: float = 0.05, suffix: str = "") -> str:
    """``edc(variant, fraction, error)`` from ``scored`` and ``curve``; names end in ``suffix``."""
    wrong = "score < t" if error == "fnmr" else "score >= t"
    x = suffix
    return f"""start{x} as (select variant, threshold as t from (select variant, threshold, row_number() over (partition by variant order by abs({error} - {start}), threshold) as r from curve) where r = 1),
eb{x} as (select variant, pair_q, count(*) as n, count(*) filter (where {wrong}) as w from scored join start{x} using (variant) where mated = {str(error == 'fnmr').lower()} group by all),
edc{x} as (select variant, coalesce(sum(n) over p, 0)::double / sum(n) over (partition by variant) as fraction, (sum(w) over (partition by variant) - coalesce(sum(w) over p, 0))::double / (sum(n) over (partition by variant) - coalesce(sum(n) over p, 0)) as error
        from eb{x} window p as (partition by variant order by pair_q rows between unbounded preceding and 1 preceding))"""


def measures() -> tuple[str, ...]:
    """``measured(variant, measure, value)`` from ``scored`` and ``curve``."""
    areas = ", ".join(
        f"""{discard(e, suffix='_' + e)},
area_{e} as (select variant, round(sum(floor((e - fraction) * error * 1e12 + 0.5))::double / 1e12, 6) as value
             from (select variant, fraction, error, least(coalesce(lead(fraction) over (partition by variant order by fraction), 1), 0.2) as e from edc_{e}) where fraction < 0.2 group by variant)"""
        for e in ("fnmr", "fmr")
    )
    return (
        areas,
        """measured as (select variant, 'eer' as measure, round((fnmr + fmr) / 2, 6) as value from (select *, row_number() over (partition by variant order by abs(fnmr - fmr), threshold) as r from curve) where r = 1
union all select variant, concat('fnmr_at_', target::varchar), round(fnmr, 6) from (select variant, target, fnmr, row_number() over (partition by variant, target order by fmr desc, fnmr) as r from curve cross join (select unnest([0.001, 0.01])::double as target) t where fmr <= target) where r = 1
union all select variant, 'pauc_fnmr', value from area_fnmr union all select variant, 'pauc_fmr', value from area_fmr)""",
    )


def with_(*parts: str) -> str:
    return "with recursive " + ",\n".join(parts)
