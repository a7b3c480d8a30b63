"""A collection with known copies, made of the given vectors: every branch of the assignment rules occurs in it.

Base image i belongs to subject s = i div 5; its features are 2*e[5s] + e[i] over the given vectors in fixed point, so that images of a subject are alike. Further images (ids from 1,000,000) by s mod 10:
0 a byte copy in the same subject; 1 a better near copy, and a crop of that copy that only the region hash finds (so that sets of two hashes overlap in it); 2 a byte copy under the next subject; 3 a blend of two
subjects in both; 4 a stranger in both; 5 one image in two subjects that have nothing else, and one in this subject and in one that has nothing else; 6 two unrelated images with one hash; 7 two alike and an outlier
with one hash; 8 a near copy without features and quality, and an image without either in two subjects; 9 a near copy in the same subject by the frequency hash alone and one under the next subject by the
region hash alone (so that their original is in sets of both kinds).
The region hash ``seg`` of an image is named after its frequency hash where nothing else is said.
The same expressions run in both engines, only the array functions differ (see ``SPARK`` and ``DUCKDB``).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

SPARK = {
    "fixed": "transform(embedding, x -> cast(floor(cast(x as double) * 32768 + 0.5) as bigint))",
    "add": "zip_with({a}, {b}, (x, y) -> {m} * x + y)",
    "noise": "transform({a}, (x, j) -> x + (j + {s}) % 3 - 1)",
    "sha": "sha2({a}, 256)",
    "long": "bigint",
    "div": "{a} div {b}",
    "text": "cast({a} as string)",
    "vector": "cast(null as array<bigint>)",
}
DUCKDB = {
    "fixed": "list_transform(embedding, lambda x: cast(floor(cast(x as double) * 32768 + 0.5) as bigint))",
    "add": "list_transform(list_zip({a}, {b}), lambda p: {m} * p[1] + p[2])",
    "noise": "list_transform({a}, lambda x, j: x + (j - 1 + {s}) % 3 - 1)",
    "sha": "sha256({a})",
    "long": "bigint",
    "div": "{a} // {b}",
    "text": "cast({a} as varchar)",
    "vector": "cast(null as bigint[])",
}


def sql(d: dict[str, str]) -> str:
    """Common table expressions ending in ``signed``; ``embeddings`` must be a table."""

    def add(a: str, b: str, m: int) -> str:
        return d["add"].format(a=a, b=b, m=m)

    def div(a: str, b: int) -> str:
        return d["div"].format(a=a, b=b)

    def text(a: str) -> str:
        return d["text"].format(a=a)

    def name(s: str) -> str:
        return f"concat('s', lpad({text(s)}, 6, '0'))"

    def extra(c: int, k: int, subject: str, content: str, hi: str, vec: str, q: str, source: str, seg: str | None = None) -> str:
        """One planted image for each subject of class c; ``source`` says for which of them."""
        return f"select 1000000 + 10 * s + {k} as image_id, {subject} as subject, {content} as content, {hi} as hi, {seg or region(hi)} as seg, {vec} as vec, {q} as q from anchors where s % 10 = {c} and {source}"

    def region(hi: str) -> str:
        return f"concat('r', {text(hi)})"

    own, other = name("s"), name("s + 1")
    c1 = f"concat('image-', {text('5 * s + 1')})"
    made = lambda tag: f"concat('{tag}-', {text('s')})"
    one = add("a0", "a1", 2)
    q1 = "cast((5 * s + 1) % 7 as double)"
    rows = [
        extra(0, 0, own, c1, "5 * s + 1", one, q1, "true"),
        extra(1, 0, own, made("near"), "5 * s + 1", d["noise"].format(a=one, s="s"), "cast(7 as double)", "true", made("crop")),
        extra(1, 1, own, made("cropped"), "7000000 + s", d["noise"].format(a=one, s="s + 1"), "cast(2 as double)", "true", made("crop")),
        extra(2, 0, other, c1, "5 * s + 1", one, q1, "s + 1 < subjects"),
        *[extra(3, k, own if k == 0 else other, made("blend"), "2000000 + s", add("a0", "b0", 1), "cast(3 as double)", "s + 1 < subjects") for k in (0, 1)],
        *[extra(4, k, own if k == 0 else other, made("stranger"), "3000000 + s", "far", "cast(3 as double)", "s + 1 < subjects") for k in (0, 1)],
        *[extra(5, k, f"concat('solo-', {text('s')}, '-{'ab'[k]}')", made("solo"), "4000000 + s", "a2", "cast(1 as double)", "true") for k in (0, 1)],
        *[extra(5, 2 + k, own if k == 0 else f"concat('alone-', {text('s')})", made("lone"), "4500000 + s", one, "cast(1 as double)", "true") for k in (0, 1)],
        *[extra(6, k, own, made(f"mixed{k}"), "5000000 + s", "far" if k else "far2", f"cast({k} as double)", "true") for k in (0, 1)],
        *[extra(7, k, own, made(f"three{k}"), "6000000 + s", "far" if k == 2 else d["noise"].format(a=one, s=f"s + {k}"), f"cast({k} as double)", "true") for k in (0, 1, 2)],
        extra(8, 0, own, made("bare"), "5 * s + 1", d["vector"], "cast(null as double)", "true"),
        *[extra(8, 1 + k, own if k == 0 else other, made("mute"), "8000000 + s", d["vector"], "cast(null as double)", "s + 1 < subjects") for k in (0, 1)],
        extra(9, 0, own, made("edited"), "5 * s + 1", d["noise"].format(a=one, s="s"), "cast(2 as double)", "true", made("other")),
        extra(9, 1, other, made("part"), "9000000 + s", d["noise"].format(a=one, s="s + 2"), "cast(2 as double)", "s + 1 < subjects", region("5 * s + 1")),
    ]
    union = " union all ".join(rows)
    return f"""
e as (select cast(vec_id as bigint) as i, {d['fixed']} as v from embeddings),
size as (select cast({div('count(*)', 5)} as bigint) as subjects from e),
base as (select x.i, {div('x.i', 5)} as s, {add('z.v', 'x.v', 2)} as vec from e x join e z on z.i = 5 * ({div('x.i', 5)})),
anchors as (select z.s, subjects, e0.v as a0, e1.v as a1, e2.v as a2, nx.v as b0, f1.v as far, f2.v as far2
            from (select distinct s from base) z cross join size join e e0 on e0.i = 5 * z.s join e e1 on e1.i = 5 * z.s + 1 join e e2 on e2.i = 5 * z.s + 2
            join e nx on nx.i = (5 * (z.s + 1)) % (5 * subjects) join e f1 on f1.i = (5 * z.s + 252) % (5 * subjects) join e f2 on f2.i = (5 * z.s + 137) % (5 * subjects)),
all_images as (select i as image_id, {name('s')} as subject, concat('image-', {text('i')}) as content, i as hi, {region('i')} as seg, vec, cast(i % 7 as double) as q from base union all {union}),
signed as (select 'planted' as dataset, cast(image_id as bigint) as image_id, concat(subject, '/', lpad({text('image_id')}, 10, '0')) as path, subject, content, cast(length(content) as bigint) as length,
           {d['sha'].format(a='content')} as digest, cast(hi as bigint) as hi, cast(0 as bigint) as lo,
           case when image_id % 50 <> 7 then cast(hi as bigint) end as ahi, case when image_id % 50 <> 7 then cast(0 as bigint) end as alo, seg, case when image_id % 50 <> 7 then seg end as aseg, vec, q from all_images)"""


def signed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The planted collection as signed rows; every fiftieth image lacks an aligned crop."""
    view = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    return spark.sql(f"with {sql(SPARK)} select * from signed".replace("from embeddings", "from {embeddings}"), embeddings=view)
