from pyspark.sql import functions as F

from keyscout.operators.discover import discover_keys
from keyscout.streaming import monitor


def batches(spark, sf, path, n=3):
    """The events table as n files of a directory, in time order."""
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("event_id")
    rows = events.withColumn("k", F.ntile(n).over(__import__("pyspark.sql", fromlist=["Window"]).Window.orderBy("event_id")))
    for k in range(1, n + 1):
        rows.where(F.col("k") == k).drop("k").coalesce(1).write.mode("append").parquet(path)
    return events


def run(df, name, mode):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_conflicts(spark, sf, tmp_path):
    events = batches(spark, sf, f"{tmp_path}/in")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    run(monitor.key_conflicts(stream, ["user_id", "event_type"]), "conflicts", "complete")
    want = events.groupBy("user_id", "event_type").count().where("count > 1")
    assert sorted(map(tuple, spark.table("conflicts").collect())) == sorted(map(tuple, want.collect()))


def test_windows_and_filter(spark, sf, tmp_path):
    events = batches(spark, sf, f"{tmp_path}/in", 2)
    stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/in")
    run(monitor.conflicts_by_window(stream, ["event_type"], "ts", "1 day"), "windows", "complete")
    want = events.groupBy(F.window(F.col("ts").cast("timestamp"), "1 day"), "event_type").count().where("count > 1")
    assert spark.table("windows").count() == want.count()
    run(monitor.first_by_key(stream, ["event_id"], "ts"), "firsts", "append")
    assert spark.table("firsts").count() == events.count()


def test_run_counters(spark, sf, tmp_path):
    events = batches(spark, sf, f"{tmp_path}/in")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    run(monitor.run_counters(stream, "user_id"), "runs", "update")
    want = events.groupBy("user_id").count().select(F.sum(F.col("count") * (F.col("count") - 1) / 2)).first()[0]
    assert spark.table("runs").agg(F.sum("new_pairs")).first()[0] == want


def test_key_set_upkeep(spark, sf, tmp_path):
    events = batches(spark, sf, f"{tmp_path}/in")
    keeper = monitor.KeySetMaintainer(f"{tmp_path}/table")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = stream.writeStream.foreachBatch(keeper).trigger(availableNow=True).start()
    q.awaitTermination()
    assert keeper.result.keys == discover_keys(events).keys and keeper.refreshed <= 3
