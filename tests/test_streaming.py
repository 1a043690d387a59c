import datetime

import pytest
from pyspark.sql import functions as F

from locpref.sources.tables import table
from locpref.streaming import checkins


@pytest.fixture()
def events(spark, small, tmp_path):
    table(spark, small, "events").write.parquet(f"{tmp_path}/in")
    return checkins.read_events(spark, f"{tmp_path}/in")


def test_sliding_counts(spark, small, events, tmp_path):
    checkins.run_to_table(checkins.sliding(events, 6, 3), "sliding", f"{tmp_path}/c")
    e = table(spark, small, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    last = e.agg(F.max("ts")).first()[0] - datetime.timedelta(hours=1)
    want = e.groupBy(F.window("ts", "6 hours", "3 hours").alias("w")).agg(F.count("*").alias("n")).where(F.col("w.end") <= F.lit(last))
    assert {(r.start, r.n) for r in spark.table("sliding").collect()} == {(r.w.start, r.n) for r in want.collect()}


def test_dedup_and_match(spark, small, tmp_path):
    e = table(spark, small, "events")
    e.unionByName(e).write.parquet(f"{tmp_path}/in")
    one = checkins.dedup(checkins.read_events(spark, f"{tmp_path}/in"))
    checkins.run_to_table(one, "once", f"{tmp_path}/c")
    assert spark.table("once").count() == e.count()
    s = checkins.read_events(spark, f"{tmp_path}/in")
    checkins.run_to_table(checkins.match(s.where("event_id % 2 = 0"), s.where("event_id % 2 = 1"), "6 hours"), "matched", f"{tmp_path}/d")
    a, v = e.where("event_id % 2 = 0").alias("a"), e.where("event_id % 2 = 1").alias("v")
    want = a.join(v, F.expr("a.user_id = v.user_id and v.ts <= a.ts and v.ts >= a.ts - interval 6 hours")).count()
    assert spark.table("matched").distinct().count() == want


def test_budget_refuses_and_survives_a_restart(spark, small, tmp_path):
    e = table(spark, small, "events").orderBy("event_id")
    half = e.count() // 2
    e.where(F.col("event_id") < half).write.parquet(f"{tmp_path}/in")
    def go():
        q = checkins.budgeted_reports(checkins.read_events(spark, f"{tmp_path}/in"), 0.1, 1.0).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
        q.awaitTermination()

    go()
    e.where(F.col("event_id") >= half).write.mode("append").parquet(f"{tmp_path}/in")
    go()
    got = spark.read.parquet(f"{tmp_path}/out").groupBy("user_id").agg(F.count_if("accepted").alias("a"), F.count("*").alias("n")).collect()
    assert sum(r.n for r in got) == e.count()
    assert all(r.a == min(10, r.n) for r in got)


def test_refit_keeps_the_last_label(spark, small, events, tmp_path):
    seen = []
    checkins.refit(events, f"{tmp_path}/t", f"{tmp_path}/c", lambda df, n: seen.append((n, df.count()))).awaitTermination()
    e = table(spark, small, "events")
    want = {(r.user_id, r.event_type): r.m.label for r in e.groupBy("user_id", "event_type").agg(F.max(F.struct("ts", "event_id", (F.col("value") >= 35).cast("int").alias("label"))).alias("m")).collect()}
    got = {(r.user_id, r.event_type): r.label for r in spark.read.parquet(f"{tmp_path}/t/{seen[-1][0]}").collect()}
    assert got == want


def test_late_rows_are_counted(spark, tmp_path):
    base = datetime.datetime(2024, 1, 1)
    rows = lambda hours: spark.createDataFrame([(i, base + datetime.timedelta(hours=h), 1, "a", 1.0, "{}") for i, h in enumerate(hours)], checkins.EVENTS)
    rows([1, 40]).coalesce(1).write.parquet(f"{tmp_path}/in")
    out = checkins.slot_counts(checkins.read_events(spark, f"{tmp_path}/in", files=1), 6)
    q = out.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination()
    rows([2, 41]).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    q = out.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination()
    assert checkins.late_metric(q) == 1


def test_permanent_bits_outlive_a_restart(spark, small, tmp_path):
    e = table(spark, small, "events").orderBy("event_id")
    half = e.count() // 2
    e.where(F.col("event_id") < half).write.parquet(f"{tmp_path}/in")

    def go():
        visits = checkins.read_events(spark, f"{tmp_path}/in").withColumnRenamed("event_type", "item")
        q = checkins.permanent_bits(visits, 0.5).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
        q.awaitTermination()

    go()
    e.where(F.col("event_id") >= half).write.mode("append").parquet(f"{tmp_path}/in")
    go()
    got = spark.read.parquet(f"{tmp_path}/out")
    assert got.count() == e.count()
    assert got.groupBy("user_id", "item").agg(F.countDistinct("ybit").alias("n")).where("n > 1").isEmpty()
    assert {r.ybit for r in got.select("ybit").distinct().collect()} == {0, 1}
