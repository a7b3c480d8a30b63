"""Relational queries on small tables made for what went wrong once."""

from twinfold.queries import surround


def _plan(df) -> str:
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_range_source_reads_orders(spark, data):
    df = surround.QUERIES["range_source"](spark, data)
    assert "o_orderkey" in _plan(df) and df.agg({"orders": "sum"}).first()[0] == spark.read.parquet(f"{data}/orders.parquet").count()


def test_sketches_are_not_held_for_each_distinct_order(spark, tmp_path):
    spark.createDataFrame([("A", 1, 5.0), ("A", 1, 7.0), ("A", 2, 7.0), (None, 3, 1.0)], "l_returnflag string, l_orderkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    df = surround.QUERIES["agg_sketches"](spark, str(tmp_path))
    assert sorted((str(r["l_returnflag"]), r["orders"], r["orders_hll"], r["exact"]) for r in df.collect()) == [("A", 2, 2, 2), ("None", 1, 1, 1)]
    aggregates = [x for x in df._jdf.queryExecution().executedPlan().toString().splitlines() if "Aggregate(" in x]
    assert not [x for x in aggregates if "hll" in x and "l_orderkey" in x.split("functions=")[0]]


def test_window_frames_round_to_the_nearest_second(spark, tmp_path):
    """A day and a second apart after rounding, a day apart after cutting."""
    spark.sql("select * from values (1L, 7L, timestamp_ntz'2024-01-01 00:00:00.4'), (2L, 7L, timestamp_ntz'2024-01-02 00:00:00.6') t(event_id, user_id, ts)").write.parquet(f"{tmp_path}/events.parquet")
    assert sorted(map(tuple, surround.QUERIES["window_frames"](spark, str(tmp_path)).collect())) == [(1, 1, 1), (2, 2, 1)]


def test_sql_cte_reads_orders(spark, data):
    last = surround.QUERIES["sql_cte"](spark, data).orderBy("i").collect()[-1]
    assert (last["i"], last["f"]) == (12, spark.read.parquet(f"{data}/orders.parquet").count())
