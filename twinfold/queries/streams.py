"""Streams over the given tables, drained once; each agrees with a batch statement."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import detect as det
from ..plans.shipping import ship
from ..plans.storage import fresh, materialise
from ..sources import catalog
from ..streaming import filters as st
from . import oracle as o

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _docs(spark, d) -> DataFrame:
    return st.arriving(spark, f"{d}/documents.parquet", DOCS)


def _events(spark, d) -> DataFrame:
    """Event time as an instant; the files carry it without a zone."""
    schema = catalog.table(spark, d, "events").schema
    return st.arriving(spark, f"{d}/events.parquet", schema).withColumn("ts", F.col("ts").cast("timestamp"))


@query("stream_exact_filter", "select distinct sha256(text) as digest from documents")
def stream_exact_filter(spark, d):
    return st.drain(st.exact_filter(st.stamped(_docs(spark, d).select("doc_id", "text"))).select("digest"))


@query("stream_vs_store", "select doc_id from documents where text not in (select text from documents where lang = 'de')")
def stream_vs_store(spark, d):
    """The store holds the digests of the German documents."""
    store = materialise(catalog.table(spark, d, "documents").where("lang = 'de'").select(F.sha2(F.col("text").cast("binary"), 256).alias("digest")).distinct(), "store")
    return st.drain(st.against_store(_docs(spark, d), store).select("doc_id"))


@query("stream_fill_store", "select sha256(text) as digest, min(doc_id) as doc_id from documents group by text")
def stream_fill_store(spark, d):
    base = fresh(spark, "store")
    st.fill_store(_docs(spark, d), f"{base}/rows", f"{base}/checkpoint")
    return spark.read.schema("digest string, doc_id long, batch long").parquet(f"{base}/rows").select("digest", "doc_id")


@query("stream_near_filter", o.with_(o.documents("source", False), "store as (select hi, lo, min(image_id) as rep from signed where subject = 'src0' group by hi, lo)") + " select distinct image_id, rep as known from signed s join store t on bit_count(xor(s.hi, t.hi)) + bit_count(xor(s.lo, t.lo)) <= 6")
def stream_near_filter(spark, d):
    """Arrivals near a stored hash; the store holds one source."""
    ship(spark)
    signed = catalog.sign(catalog.documents(spark, d).where("subject = 'src0'"), ("dct",))
    store = materialise(signed.groupBy("hi", "lo").agg(F.min("image_id").alias("rep")), "store")
    s = _docs(spark, d).select(F.lit("documents").alias("dataset"), F.col("doc_id").alias("image_id"), F.lit("").alias("path"), F.col("source").alias("subject"), F.col("text").alias("content"))
    return st.drain(st.near_filter(catalog.sign(s, ("dct",)), store)).distinct()


@query("stream_keep_changes")
def stream_keep_changes(spark, d):
    """Digest - smallest path as state; after one pass every digest is kept once."""
    ship(spark)
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        rows = _docs(spark, d).select("text", F.concat("source", F.lit("/"), catalog.padded("doc_id")).alias("path"))
        return st.drain(st.keep_changes(rows), "append", "keep")
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)


def _window(name: str, made, sql: str):
    @query(name, sql)
    def run(spark, d):
        e = _events(spark, d).withWatermark("ts", "1 hour")
        out = e.groupBy(made().alias("w"), "event_type").agg(F.count("*").alias("n"))
        return st.drain(out, "complete", name).select(F.unix_timestamp("w.start").alias("start"), F.unix_timestamp("w.end").alias("end"), "event_type", "n")


_window("stream_tumbling", lambda: F.window("ts", "1 day"), "select floor(epoch(ts) / 86400)::bigint * 86400 as start, floor(epoch(ts) / 86400)::bigint * 86400 + 86400 as end, event_type, count(*) as n from events group by all")
_window("stream_sliding", lambda: F.window("ts", "2 hours", "1 hour"), "select s as start, s + 7200 as end, event_type, count(*) as n from (select event_type, unnest([floor(epoch(ts) / 3600)::bigint * 3600 - 3600, floor(epoch(ts) / 3600)::bigint * 3600]) as s from events) group by all")


@query("stream_session", """with e as (select user_id, ts, case when ts - lag(ts) over w < interval 6 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as k from e) select user_id, floor(epoch(min(ts)))::bigint as start, count(*) as n from s group by user_id, k""")
def stream_session(spark, d):
    """Sessions of a user end after six hours without an event."""
    e = _events(spark, d).withWatermark("ts", "1 hour")
    out = e.groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return st.drain(out, "complete", "session").select("user_id", F.unix_timestamp("w.start").alias("start"), "n")


@query("stream_join", "select v.event_id as view_id, c.event_id as click_id from events v join events c on v.user_id = c.user_id and v.event_type = 'view' and c.event_type = 'click' and c.ts between v.ts and v.ts + interval 1 hour")
def stream_join(spark, d):
    v = _events(spark, d).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("vu"), F.col("ts").alias("vt")).withWatermark("vt", "2 hours")
    c = _events(spark, d).where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")).withWatermark("ct", "2 hours")
    return st.drain(v.join(c, F.expr("vu = cu and ct between vt and vt + interval 1 hour")).select("view_id", "click_id"))


def _in_two(spark, d, first: str, name: str):
    """Events as a folder that gets a second file after the first run; ``arrived(k)`` is the stream over the first k files."""
    base = fresh(spark, name)
    e = catalog.table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    parts = [e.where(first), e.where(f"not ({first})")]

    def arrived(k: int) -> DataFrame:
        parts[k - 1].coalesce(1).write.mode("append").parquet(f"{base}/in/{k}")
        return st.arriving(spark, f"{base}/in/*", "event_id long, ts timestamp, event_type string")

    return arrived, f"{base}/mark"


_LATE = "event_id % 10 <> 0"


@query("stream_late", f"select count(*) as events, count(*) filter (where {_LATE} or ts > cut) as on_time, count(*) filter (where not ({_LATE}) and ts <= cut) as late from events cross join (select date_trunc('millisecond', max(ts)) - interval 1 day as cut from events where {_LATE})")
def stream_late(spark, d):
    """Nine tenths of the events first; of the rest, which arrives in a second run, what lies a day behind the newest event is late and dropped."""
    arrived, mark = _in_two(spark, d, _LATE, "late")
    for k in (1, 2):
        kept = st.drain(arrived(k).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]), checkpoint=mark)
    n = catalog.table(spark, d, "events").count()
    return kept.agg(F.count("*").alias("on_time")).select(F.lit(n).cast("long").alias("events"), "on_time", (F.lit(n) - F.col("on_time")).cast("long").alias("late"))


@query("stream_restart", "select event_id, event_type from events")
def stream_restart(spark, d):
    """A run that ends and starts again on its checkpoint reads every event once; its file sink holds each exactly once."""
    arrived, mark = _in_two(spark, d, "event_id % 2 = 0", "restart")
    for k in (1, 2):
        rows = st.drain(arrived(k).select("event_id", "event_type"), checkpoint=mark)
    return rows


@query("stream_update", "select floor(epoch(ts) / 86400)::bigint * 86400 as start, event_type, count(*) as n from events group by all")
def stream_update(spark, d):
    """Counts a day in update mode: each batch emits what changed, and the largest count of a window is its last."""
    e = _events(spark, d).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    rows = st.drain(e, "update", "update")
    return rows.groupBy(F.unix_timestamp("w.start").alias("start"), "event_type").agg(F.max("n").alias("n"))
