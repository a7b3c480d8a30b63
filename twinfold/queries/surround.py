"""The relational, functional and format operators around the methods, on the given tables."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..operators import detect as det
from ..plans import report
from ..plans.shipping import ship
from ..plans.storage import fresh
from ..sources.catalog import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


# ---- scans, sinks, projection, filter

@query("scan_parquet", "select l_orderkey, l_linenumber, l_quantity from lineitem where l_quantity >= 45")
def scan_parquet(spark, d):
    return table(spark, d, "lineitem").where("l_quantity >= 45").select("l_orderkey", "l_linenumber", "l_quantity")


@query("range_source", "select range as id, range * range % 97 as r, count(o_orderkey) as orders from range(1000) left join orders on o_orderkey % 1000 = range group by range")
def range_source(spark, d):
    """A generated range, and how many orders fall to each of its numbers."""
    per = table(spark, d, "orders").groupBy((F.col("o_orderkey") % 1000).alias("id")).agg(F.count("o_orderkey").alias("orders"))
    return spark.range(1000).join(per, "id", "left").select("id", (F.col("id") * F.col("id") % 97).alias("r"), F.coalesce("orders", F.lit(0)).alias("orders"))


def _trip(spark, d, fmt: str) -> DataFrame:
    path = fresh(spark, f"trip-{fmt}")
    src = table(spark, d, "events").select("event_id", "event_type", "props")
    schema = "event_id long, event_type string, props string"
    w = src.write.mode("overwrite")
    if fmt == "csv":
        w.option("header", True).option("quoteAll", True).option("escape", '"').csv(path)
        return spark.read.schema(schema + ", _bad string").option("columnNameOfCorruptRecord", "_bad").option("mode", "PERMISSIVE").option("header", True).option("escape", '"').csv(path).select("event_id", "event_type", "props")
    if fmt == "text":
        src.select(F.to_json(F.struct("*")).alias("value")).write.mode("overwrite").text(path)
        return spark.read.text(path).select(F.from_json("value", schema).alias("x")).select("x.*")
    getattr(w, fmt)(path)
    return getattr(spark.read.schema(schema), fmt)(path)


@query("roundtrip_formats", "select f as format, event_id, event_type, props from events cross join (select unnest(['csv', 'json', 'orc', 'text']) as f)")
def roundtrip_formats(spark, d):
    out = None
    for fmt in ("csv", "json", "orc", "text"):
        one = _trip(spark, d, fmt).select(F.lit(fmt).alias("format"), "event_id", "event_type", "props")
        out = one if out is None else out.unionByName(one)
    return out


@query("sink_partitioned", "select lang, count(*) as documents, cast(sum(n_chars) as bigint) as chars from documents group by lang")
def sink_partitioned(spark, d):
    """Partitioned, sorted, idempotent (overwrites only the partitions it writes)."""
    path = fresh(spark, "by-lang")
    src = table(spark, d, "documents").select("doc_id", "n_chars", "lang")
    for _ in range(2):
        src.repartition("lang").sortWithinPartitions("doc_id").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("lang").parquet(path)
    return spark.read.schema("doc_id long, n_chars long, lang string").parquet(path).groupBy("lang").agg(F.count("*").alias("documents"), F.sum("n_chars").alias("chars"))


@query("sink_actions", "select concat(source, '/', lpad(cast(doc_id as varchar), 10, '0')) as path, 'remove' as action from (select *, row_number() over (partition by text order by concat(source, '/', lpad(cast(doc_id as varchar), 10, '0'))) as r from documents) where r > 1")
def sink_actions(spark, d):
    """The published list of removals, one sorted file: only this small list is brought together."""
    from ..sources.catalog import documents

    c = det.with_digest(documents(spark, d)).select("digest", "path")
    gone = c.join(c.groupBy("digest").agg(F.min("path").alias("keep")), "digest").where("path <> keep").select("path", F.lit("remove").alias("action"))
    path = fresh(spark, "actions")
    gone.repartitionByRange(1, "path").sortWithinPartitions("path").write.mode("overwrite").option("header", True).csv(path)
    return spark.read.schema("path string, action string").option("header", True).csv(path)


@query("project_nested", "select doc_id, {'s': source, 'l': lang}.s as s, cast(n_chars as double) / 2 as half from documents")
def project_nested(spark, d):
    x = table(spark, d, "documents").select("doc_id", F.struct(F.col("source").alias("s"), F.col("lang").alias("l")).alias("k"), F.col("n_chars"), F.lit(1).alias("unused"))
    return x.withColumns({"half": F.col("n_chars").cast("double") / 2}).drop("unused").select("doc_id", "k.s", "half")


@query("filter_predicates", "select doc_id from documents where lang in ('en', 'fr') and n_chars between 200 and 2000 and source like 'src1%' and regexp_matches(text, '[0-9]{2}') and source is not distinct from source and len(list_filter(string_split(text, ' '), lambda w: length(w) > 12)) > 0")
def filter_predicates(spark, d):
    t = table(spark, d, "documents")
    return t.where(F.col("lang").isin("en", "fr") & F.col("n_chars").between(200, 2000) & F.col("source").like("src1%") & F.col("text").rlike("[0-9]{2}") & F.col("source").eqNullSafe(F.col("source")) & F.exists(F.split("text", " "), lambda w: F.length(w) > 12)).select("doc_id")


# ---- joins

@query("join_equi", "select o_orderkey, c_name, o_totalprice from orders join customer on o_custkey = c_custkey where o_totalprice > 300000")
def join_equi(spark, d):
    return table(spark, d, "orders").where("o_totalprice > 300000").hint("merge").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name", "o_totalprice")


@query("join_broadcast", "select n_name, count(*) as customers from customer join nation on c_nationkey = n_nationkey group by n_name")
def join_broadcast(spark, d):
    return table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("customers"))


@query("join_outer", "select coalesce(d.doc_id, l.doc_id) as doc_id, d.lang, l.quality from (select doc_id, lang from documents where lang = 'en') d full join (select * from labels where toxic = 0) l on d.doc_id = l.doc_id")
def join_outer(spark, d):
    a, b = table(spark, d, "documents").where("lang = 'en'").select("doc_id", "lang"), table(spark, d, "labels").where("toxic = 0").select("doc_id", "quality")
    return a.join(b, "doc_id", "full_outer")


@query("join_semi", "select doc_id from documents where doc_id in (select doc_id from labels where quality = 0)")
def join_semi(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").where("quality = 0"), "doc_id", "left_semi")


@query("join_anti", "select doc_id from documents where doc_id not in (select doc_id from labels)")
def join_anti(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left_anti")


@query("join_theta", "select x.conv_id, x.turn as a, y.turn as b from conversations x join conversations y on x.conv_id = y.conv_id and x.turn < y.turn and x.role <> y.role")
def join_theta(spark, d):
    c = table(spark, d, "conversations").select("conv_id", "turn", "role")
    a, b = c.alias("a"), c.alias("b")
    return a.join(b, (F.col("a.conv_id") == F.col("b.conv_id")) & (F.col("a.turn") < F.col("b.turn")) & (F.col("a.role") != F.col("b.role"))).select(F.col("a.conv_id").alias("conv_id"), F.col("a.turn").alias("a"), F.col("b.turn").alias("b"))


@query("join_range", "select n_chars_lo as lo, count(*) as documents from documents join (select unnest(range(0, 40000, 500)) as n_chars_lo) on n_chars >= n_chars_lo and n_chars < n_chars_lo + 700 group by 1")
def join_range(spark, d):
    """Overlapping ranges of 700 every 500: an equi join on bins of 500, then the exact bounds."""
    r = spark.range(0, 40000, 500).select(F.col("id").alias("lo"), F.explode(F.array(F.floor(F.col("id") / 500), F.floor((F.col("id") + 699) / 500))).alias("bin"))
    t = table(spark, d, "documents").select("n_chars", F.floor(F.col("n_chars") / 500).alias("bin"))
    return t.join(r.distinct(), "bin").where("n_chars >= lo and n_chars < lo + 700").groupBy("lo").agg(F.count("*").alias("documents"))


@query("join_asof", "select e.event_id, p.event_id as seen from events e asof left join (select * from events where event_type = 'view') p on e.user_id = p.user_id and e.ts >= p.ts where e.event_type = 'click'")
def join_asof(spark, d):
    """Each click with the last view of its user up to then: one window over the union, no inequality join."""
    e = table(spark, d, "events").where("event_type in ('view', 'click')").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type").desc()).rowsBetween(Window.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w)
    return e.withColumn("seen", seen).where("event_type = 'click'").select("event_id", "seen")


@query("join_interval", "select v.event_id as view_id, c.event_id as click_id from events v join events c on v.user_id = c.user_id and v.event_type = 'view' and c.event_type = 'click' and c.ts between v.ts and v.ts + interval 1 hour")
def join_interval(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    v, c = e.where("event_type = 'view'").alias("v"), e.where("event_type = 'click'").alias("c")
    return v.join(c, F.expr("v.user_id = c.user_id and c.ts between v.ts and v.ts + interval 1 hour")).select(F.col("v.event_id").alias("view_id"), F.col("c.event_id").alias("click_id"))


@query("join_lateral", "select c_custkey, o_orderkey from customer, lateral (select o_orderkey from orders where o_custkey = c_custkey order by o_totalprice desc, o_orderkey limit 2)")
def join_lateral(spark, d):
    c, o = table(spark, d, "customer").select("c_custkey"), table(spark, d, "orders")
    top = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return c.lateralJoin(top)


# ---- aggregation

@query("agg_basic", "select l_returnflag, l_linestatus, cast(sum(l_quantity) as bigint) as quantity, count(*) as n, max(l_extendedprice) as top from lineitem group by all")
def agg_basic(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("long").alias("quantity"), F.count("*").alias("n"), F.max("l_extendedprice").alias("top"))


@query("agg_collect", "select lang, array_to_string(list_sort(list(distinct source)), ',') as sources from documents group by lang")
def agg_collect(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.array_join(F.array_sort(F.collect_set("source")), ",").alias("sources"))


@query("agg_distinct", "select event_type, count(distinct user_id) as users, count(distinct cast(ts as date)) as days from events group by event_type")
def agg_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.to_date("ts")).alias("days"))


@query("agg_sketches")
def agg_sketches(spark, d):
    """Approximate distinct counts, quantiles and frequencies: for planning, never for reported counts."""
    t = table(spark, d, "lineitem")
    sketched = t.groupBy("l_returnflag").agg(
        F.approx_count_distinct("l_orderkey").alias("orders"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("orders_hll"), F.percentile_approx("l_quantity", 0.5).alias("median")
    )
    # apart from the sketches: in one aggregation each distinct order would hold sketches of its own first
    exact = t.groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_distinct("l_orderkey").alias("exact"))
    return sketched.join(exact, F.col("l_returnflag").eqNullSafe(F.col("flag"))).drop("flag")


@query("agg_grouping_sets", "select lang, source, count(*) as n, cast(grouping(lang) * 2 + grouping(source) as bigint) as g from documents group by grouping sets ((lang, source), (lang), ())")
def agg_grouping_sets(spark, d):
    return table(spark, d, "documents").groupingSets([["lang", "source"], ["lang"], []], "lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("agg_cube", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def agg_cube(spark, d):
    return table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("agg_rollup", "select lang, source, cast(sum(n_chars) as bigint) as chars from documents group by rollup (lang, source)")
def agg_rollup(spark, d):
    return table(spark, d, "documents").rollup("lang", "source").agg(F.sum("n_chars").alias("chars"))


@query("agg_pivot", "select source, count(*) filter (where lang = 'de') as de, count(*) filter (where lang = 'en') as en, count(*) filter (where lang = 'fr') as fr from documents group by source")
def agg_pivot(spark, d):
    return table(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "fr"]).count().fillna(0)


@query("unpivot", "select doc_id, 'quality' as measure, quality as value from labels union all select doc_id, 'toxic', toxic from labels")
def unpivot(spark, d):
    return table(spark, d, "labels").unpivot("doc_id", ["quality", "toxic"], "measure", "value")


@query("agg_by", "select lang, arg_max(doc_id, (n_chars, doc_id)) as longest, arg_min(doc_id, (n_chars, doc_id)) as shortest, bool_and(n_chars > 0) as filled from documents group by lang")
def agg_by(spark, d):
    key = F.struct("n_chars", "doc_id")
    return table(spark, d, "documents").groupBy("lang").agg(F.max_by("doc_id", key).alias("longest"), F.min_by("doc_id", key).alias("shortest"), F.bool_and(F.col("n_chars") > 0).alias("filled"))


# ---- windows, sorting, sets

@query("window_ranking", "select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd, ntile(4) over w as nt from (select *, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey) as one from orders) window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def window_ranking(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    names = {"rn": F.row_number(), "rk": F.rank(), "dr": F.dense_rank(), "nt": F.ntile(4)}
    return table(spark, d, "orders").select("o_orderkey", *[f.over(w).cast("long").alias(k) for k, f in names.items()], F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("window_analytic", "select event_id, lag(event_id) over w as before, lead(event_id, 2) over w as after, first_value(event_id) over w as first, nth_value(event_id, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second from events window w as (partition by user_id order by ts, event_id)")
def window_analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query("window_frames", "select event_id, count(*) over (partition by user_id order by ts, event_id rows between 3 preceding and current row) as four, count(*) over (partition by user_id order by epoch(ts)::bigint range between 86400 preceding and current row) as day from events")
def window_frames(spark, d):
    t = table(spark, d, "events").withColumn("sec", F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long"))  # the nearest second, as the SQL's cast
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    span = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return t.select("event_id", F.count("*").over(rows).alias("four"), F.count("*").over(span).alias("day"))


@query("sort_limit", "select o_orderkey, o_totalprice from orders order by o_totalprice desc nulls last, o_orderkey limit 20 offset 5")
def sort_limit(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc_nulls_last("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query("topk_per_group", "select lang, doc_id from (select lang, doc_id, row_number() over (partition by lang order by n_chars desc, doc_id) as r from documents) where r <= 3")
def topk_per_group(spark, d):
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return table(spark, d, "documents").withColumn("r", F.row_number().over(w)).where("r <= 3").select("lang", "doc_id")


@query("set_ops", "select 'intersect' as op, doc_id from (select doc_id from documents intersect select doc_id from labels) union all select 'except', doc_id from (select doc_id from documents except select doc_id from labels) union all select 'union', doc_id from (select doc_id from documents union select doc_id from labels)")
def set_ops(spark, d):
    a, b = table(spark, d, "documents").select("doc_id"), table(spark, d, "labels").select("doc_id")
    made = {"intersect": a.intersect(b), "except": a.exceptAll(b).distinct(), "union": a.unionByName(b).distinct()}
    out = None
    for op, x in made.items():
        y = x.select(F.lit(op).alias("op"), "doc_id")
        out = y if out is None else out.unionByName(y)
    return out


# ---- functions

@query("fn_string", r"select page_id, lower(regexp_extract(url, '^[a-z]+://([^/]+)', 1)) as host, lpad(cast(page_id as varchar), 8, '0') as padded, upper(substr(url, 1, 5)) as head, regexp_replace(url, '[0-9]+', '#', 'g') as masked, cast(levenshtein(substr(url, 1, 20), substr(url, 5, 20)) as int) as distance, hex(encode(substr(url, 1, 4))) as hexed, concat_ws('-', 'a', cast(page_id as varchar)) as joined from pages")
def fn_string(spark, d):
    u = F.col("url")
    return table(spark, d, "pages").select("page_id", F.lower(F.regexp_extract(u, r"^[a-z]+://([^/]+)", 1)).alias("host"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"), F.upper(F.substring(u, 1, 5)).alias("head"), F.regexp_replace(u, "[0-9]+", "#").alias("masked"), F.levenshtein(F.substring(u, 1, 20), F.substring(u, 5, 20)).alias("distance"), F.hex(F.encode(F.substring(u, 1, 4), "UTF-8")).alias("hexed"), F.concat_ws("-", F.lit("a"), F.col("page_id").cast("string")).alias("joined"))


@query("fn_bits", "select doc_id, cast(bit_count(doc_id) as int) as ones, xor(doc_id, 255::bigint) as x, doc_id >> 2 as r from documents")
def fn_bits(spark, d):
    c = F.col("doc_id")
    return table(spark, d, "documents").select("doc_id", F.bit_count(c).alias("ones"), c.bitwiseXOR(F.lit(255)).alias("x"), F.shiftright(c, 2).alias("r"))


@query("fn_math", "select o_orderkey, round(sqrt(o_totalprice), 4) as root, cast(floor(log2(o_totalprice)) as bigint) as bits, least(o_totalprice, 1000.0) as low, cast(((o_orderkey % 7) + 7) % 7 as bigint) as m, round(cos(o_totalprice), 6) as c from orders")
def fn_math(spark, d):
    p = F.col("o_totalprice")
    return table(spark, d, "orders").select("o_orderkey", F.round(F.sqrt(p), 4).alias("root"), F.floor(F.log2(p)).alias("bits"), F.least(p, F.lit(1000.0)).alias("low"), F.pmod("o_orderkey", F.lit(7)).cast("long").alias("m"), F.round(F.cos(p), 6).alias("c"))


@query("fn_date", "select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as month, cast(datediff('day', cast(o_orderdate as date), date '1998-12-31') as int) as days, cast(year(o_orderdate) as int) as y, epoch(o_orderdate)::bigint as secs, strftime(o_orderdate + interval 3 day, '%Y-%m-%d') as later from orders")
def fn_date(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", o), "yyyy-MM-dd").alias("month"), F.datediff(F.lit("1998-12-31").cast("date"), o).alias("days"), F.year(o).alias("y"), F.unix_timestamp(o).alias("secs"), F.date_format(o + F.make_interval(days=F.lit(3)), "yyyy-MM-dd").alias("later"))


@query("fn_array", "select vec_id, cast(len(list_filter(embedding, lambda x: x > 0)) as int) as up, list_bool_and(list_transform(embedding, lambda x: abs(x) <= 1)) as unit, embedding[1:3][2] > 0 as second, list_sort(list_transform(embedding[1:4], lambda x: cast(floor(x * 100) as bigint)))[1] as least from embeddings")
def fn_array(spark, d):
    e = F.col("embedding")
    return table(spark, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).alias("up"), F.forall(e, lambda x: F.abs(x) <= 1).alias("unit"), (F.slice(e, 1, 3)[1] > 0).alias("second"), F.array_sort(F.transform(F.slice(e, 1, 4), lambda x: F.floor(x * 100)))[0].alias("least"))


@query("fn_map", "select lang, source, count(*) as n from documents where source <> 'src0' group by all")
def fn_map(spark, d):
    per = table(spark, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n")).groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return per.select("lang", F.explode(F.map_filter("m", lambda k, v: k != "src0")).alias("source", "n"))


@query("fn_json", "select event_id, json_extract_string(props, '$.k') as k, json_keys(props)[1] as first_key from events")
def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"), F.json_object_keys("props")[0].alias("first_key"))


@query("fn_null", "select d.doc_id, coalesce(l.quality, -1) as q, nullif(l.toxic, 0) as t, l.quality is not distinct from null as missing from documents d left join labels l using (doc_id)")
def fn_null(spark, d):
    t = table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left")
    return t.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.nullif("toxic", F.lit(0)).alias("t"), F.col("quality").eqNullSafe(F.lit(None)).alias("missing"))


# ---- SQL surface, UDFs, UDTF, partition functions, sampling

_CTE = "with recursive m as (select cast(month(o_orderdate) as bigint) as i, count(*) as c from {0} group by 1), n(i, f) as (select i, c from m where i = 1 union all select m.i, n.f + m.c from n join m on m.i = n.i + 1) select i, f from n"


@query("sql_cte", _CTE.format("orders"))
def sql_cte(spark, d):
    """A plain and a recursive table expression: running numbers of orders over the months of the year."""
    return spark.sql(_CTE.format("{orders}"), orders=table(spark, d, "orders"))


@query("sql_surface", "select source, count(*) as n from documents where n_chars > 1000 group by source")
def sql_surface(spark, d):
    """A parameterised statement over a passed table and the registered functions."""
    from ..functions.registry import register

    register(spark)
    return spark.sql("select source, count(*) as n from {docs} where n_chars > :low group by source", docs=table(spark, d, "documents"), args={"low": 1000})


@query("udf_scalar")
def udf_scalar(spark, d):
    from ..functions.registry import register

    register(spark)
    return spark.sql("select doc_id, blake3(cast(text as binary)) as digest from {docs}", docs=table(spark, d, "documents"))


@query("udaf_vector_mean", "select label, cast(list_position(m, list_max(m)) - 1 as bigint) as at from (select label, list(x order by p) as m from (select label, p, round(sum(x) / count(*), 7) as x from (select label, unnest(embedding)::double as x, generate_subscripts(embedding, 1) as p from embeddings) group by all) group by label)")
def udaf_vector_mean(spark, d):
    """Mean vector of each label by a grouped aggregate; its largest coordinate is returned."""
    from ..functions.registry import register

    register(spark)
    e = table(spark, d, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v"))
    m = e.groupBy("label").agg(F.call_function("vector_mean", F.col("v")).alias("m"))
    return m.select("label", (F.array_position("m", F.array_max("m")) - 1).alias("at"))


@query("udtf_bands", "select doc_id, i as band, cast('0x' || substr(md5(text), 4 * i + 1, 4) as bigint) as value from documents cross join (select unnest(range(4)) as i)")
def udtf_bands(spark, d):
    """The bands of a 64-bit value as a table function, called laterally."""
    from ..functions.registry import register

    register(spark)
    docs = table(spark, d, "documents").select("doc_id", F.substring(F.md5(F.col("text").cast("binary")), 1, 16).alias("h"))
    return spark.sql("select doc_id, b.band, b.value from {docs}, lateral hash_bands(h, 4) b", docs=docs)


@query("cogroup_compare")
def cogroup_compare(spark, d):
    """Two tables meet group by group: documents and labels of each remainder of the id, compared by counts."""
    ship(spark)
    a = table(spark, d, "documents").select("doc_id").withColumn("k", F.col("doc_id") % 64)
    b = table(spark, d, "labels").select("doc_id").withColumn("k", F.col("doc_id") % 64)

    def work(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        k = int((x if len(x) else y)["k"].iloc[0])
        return pd.DataFrame({"k": [k], "documents": [len(x)], "labelled": [int(x["doc_id"].isin(y["doc_id"]).sum())]})

    return a.groupBy("k").cogroup(b.groupBy("k")).applyInPandas(work, "k long, documents long, labelled long")


@query("sample_hash", "select doc_id from documents where cast('0x' || substr(md5(concat('5:', doc_id)), 1, 6) as bigint) < 1677721")
def sample_hash(spark, d):
    """A tenth of the rows, the same on every run and every partitioning."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit("5:"), F.col("doc_id").cast("string"))), 1, 6), 16, 10).cast("long")
    return table(spark, d, "documents").where(h < 1677721).select("doc_id")


@query("skew_report", "select cast(sum(n) as bigint) as rows, count(*) as keys, max(n) as largest, round(max(n)::double / sum(n), 6) as share from (select count(*) as n from documents group by source)")
def skew_report(spark, d):
    return report.skew(table(spark, d, "documents"), "source")


@query("agg_salted", "select l_returnflag, cast(sum(l_quantity) as bigint) as total from lineitem group by l_returnflag")
def agg_salted(spark, d):
    """A hot key summed in two steps."""
    rows = table(spark, d, "lineitem").select("l_returnflag", F.col("l_quantity").cast("long").alias("q"), "l_orderkey", "l_linenumber")
    return report.salted_sum(rows, "l_returnflag", "q", 16)
