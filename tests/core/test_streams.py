"""Streams give what the batch gives."""

from pyspark.sql import functions as F

from topicgrid.sources.tables import table
from topicgrid.streaming import online


def files(spark, sf, tmp_path, n=3):
    e = table(spark, sf, "events")
    path = f"{tmp_path}/in"
    e.repartition(n).write.parquet(path)
    return path, e


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_workload_stream_equals_batch(spark, sf, tmp_path):
    path, e = files(spark, sf, tmp_path)
    out, check = f"{tmp_path}/out", f"{tmp_path}/check"
    s = online.event_stream(spark, path, e.schema)
    online.run_workload(s, out, check).awaitTermination(120)
    want = rows(online.online_workload(e))
    assert rows(online.latest_cells(spark, out)) == want
    online.run_workload(s, out, check).awaitTermination(120)  # nothing new: the same totals
    assert rows(online.latest_cells(spark, out)) == want


def test_windows_and_repeats(spark, sf, tmp_path):
    path, e = files(spark, sf, tmp_path, 1)
    e.write.mode("append").parquet(path)  # every event twice
    s = online.without_repeats(online.with_time(online.event_stream(spark, path, e.schema, 99), "60 days"))
    q = online.window_stamps(s, "1 day").writeStream.outputMode("complete").format("memory").queryName("stamps_out").trigger(availableNow=True).start()
    q.awaitTermination(120)
    batch = online.window_stamps(e.withColumn("ts", F.col("ts").cast("timestamp")), "1 day")
    assert rows(spark.table("stamps_out")) == rows(batch)


def test_placement_keeps_groups(spark, sf, tmp_path):
    path, e = files(spark, sf, tmp_path)
    s = online.placed_online(online.event_stream(spark, path, e.schema).filter("user_id IS NOT NULL"), 4)
    q = s.writeStream.outputMode("update").format("memory").queryName("placed_out").trigger(availableNow=True).start()
    q.awaitTermination(120)
    out = spark.table("placed_out")
    assert out.groupBy("row_id").agg(F.count_distinct("grp").alias("k")).filter("k > 1").isEmpty()
    last = {r.row_id: r.n for r in out.groupBy("row_id").agg(F.max("n").alias("n")).collect()}
    assert last == {r.user_id: r.n for r in e.filter("user_id IS NOT NULL").groupBy("user_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert out.filter("grp < 0 OR grp > 3").isEmpty()


def test_lightest_groups_get_new_rows(spark, sf, tmp_path):
    path, e = files(spark, sf, tmp_path, 4)
    p = online.Placement(spark, f"{tmp_path}/placed", 4)
    s = online.event_stream(spark, path, e.schema)
    p.run(s, f"{tmp_path}/check").awaitTermination(180)
    want = {r.user_id: r.n for r in e.filter("user_id IS NOT NULL").groupBy("user_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert {r.row_id: r.n for r in p.rows().collect()} == want
    assert spark.read.parquet(p.path).groupBy("row_id").agg(F.count_distinct("grp").alias("k")).filter("k > 1").isEmpty()
    assert sum(p.loads()) == sum(want.values()) and p.drift().count() == 4
    first = p.drift().orderBy("batch").first()  # all rows are new; what known ones add later stays with them
    longest = spark.read.parquet(p.path).filter("batch = 0").agg(F.max("n")).first()[0]
    assert first.heaviest <= first.mean + longest and p.drift().filter("heaviest < mean").isEmpty()
    assert [round(x, 6) for x in p.shares([10, 0, 4], 7)] == [0, 5.5, 1.5] and p.shares([0, 0], 0) == [0, 0]


def test_late_rows_are_counted(spark, tmp_path):
    import datetime as dt

    day = lambda d: dt.datetime(2024, 1, d)
    for k, days in enumerate(([1, 2, 20], [3, 21], [4, 22])):
        spark.createDataFrame([(100 * k + d, day(d), d) for d in days], "event_id bigint, ts timestamp, user_id bigint").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    s = online.with_time(online.event_stream(spark, f"{tmp_path}/in", spark.read.parquet(f"{tmp_path}/in").schema), "2 days")
    q = online.window_stamps(s, "1 day").writeStream.outputMode("append").format("memory").queryName("late_out").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert online.late_rows(q) >= 1
