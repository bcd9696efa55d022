"""Storage layouts and what streams do with late rows."""

import time

from pyspark.sql import functions as F

from keysieve.operators import relational as O
from keysieve.sources import tables as S
from keysieve.streaming import streams as ST


def test_bucketed_tables_join_without_moving_rows(spark, sf):
    a = S.save_bucketed(S.table(spark, sf, "orders", ["o_orderkey", "o_custkey"]), "o_orderkey", 4, "bucketed_orders")
    b = S.save_bucketed(S.table(spark, sf, "lineitem", ["l_orderkey", "l_quantity"]), "l_orderkey", 4, "bucketed_lines")
    joined = O.join(a, b, a.o_orderkey == b.l_orderkey, strategy="merge")
    plan = joined._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "SortMergeJoin" in plan
    assert joined.count() == S.table(spark, sf, "lineitem").count()
    for name in ("bucketed_orders", "bucketed_lines"):
        spark.sql(f"drop table {name}")


def test_late_rows_are_counted(spark, sf):
    path = S.shared_dir(spark)
    events = S.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    # a batch is held against the watermark that the batch before it began with, so rows are late from the third on
    new, more, old = events.filter("ts >= '2024-01-25'"), events.filter("ts >= '2024-01-20' and ts < '2024-01-25'"), events.filter("ts < '2024-01-10'")
    for i, part in enumerate((new, more, old)):  # files are read by age
        time.sleep(1.1 * (i > 0))
        part.coalesce(1).write.mode("append").parquet(f"{path}/late.parquet")
        assert part.count() > 0, i
    late = ST.late_rows(ST.source(spark, path, "late", files=1), "1 day")
    # rows are told after they were combined by day and type
    assert late == old.select(F.to_date("ts"), "event_type").distinct().count() > 0


def test_range_and_asof_joins(spark):
    a = spark.createDataFrame([(i,) for i in range(0, 100, 7)], "x long")
    r = spark.createDataFrame([(0, 10), (5, 60), (60, 60)], "lo long, hi long")
    got = {(t.x, t.lo) for t in O.range_join(a, "x", r, "lo", "hi", 16).collect()}
    assert got == {(x, lo) for x in range(0, 100, 7) for lo, hi in ((0, 10), (5, 60), (60, 60)) if lo <= x <= hi}
    left = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k long, t long")
    right = spark.createDataFrame([(1, 2, "a"), (1, 4, "b"), (1, 6, "c")], "k long, t long, v string")
    assert {(r.k, r.t): r.v for r in O.asof(left, right, "k", "t", "v").collect()} == {(1, 5): "b", (1, 1): None, (2, 9): None}
