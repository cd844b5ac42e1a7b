import numpy as np
from pyspark.sql import functions as F

from meshspan.operators import moments, partition, topology
from meshspan.sources import features, tables
from meshspan.streaming import incremental

SF = "/root/testdata/sf0.001"


def test_streamed_moments_equal_batch(spark, tmp_path):
    samples = partition.by_hash(features.embeddings(spark, SF, 4), 3).select("node", "features")
    samples.repartition(4).write.parquet(str(tmp_path / "in"))
    stream = tables.stream_table(spark, str(tmp_path / "in"), samples.schema, files_per_batch=1)
    incremental.accumulate(stream, str(tmp_path / "out"), str(tmp_path / "check")).awaitTermination()
    total = incremental.accumulated(spark, str(tmp_path / "out"))
    a, b = moments.stacked(total.toPandas())[1], moments.stacked(moments.local_scatter(samples).toPandas())[1]
    assert np.allclose(a, b)
    q = incremental.refreshed(total, topology.complete(3).weights(), 2, [10] * 5)
    warm = incremental.refreshed(total, topology.complete(3).weights(), 2, [10] * 2, q[0])
    assert warm.shape == (3, 4, 2)


def test_late_events_are_dropped(spark, tmp_path):
    def event(i, ts):
        return (i, ts, i % 2, float(i))

    schema = "event_id long, ts timestamp_ntz, user_id long, value double"
    for k, rows in enumerate([[event(1, "2024-01-02 10:00:00")], [event(2, "2024-01-05 10:00:00")], [event(3, "2024-01-02 11:00:00"), event(2, "2024-01-05 10:00:00")]]):
        df = spark.createDataFrame(rows, "event_id long, ts string, user_id long, value double").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        files = spark.readStream.schema(schema).parquet(str(tmp_path / "in"))
        counted = incremental.windowed_activity(incremental.distinct_events(incremental.event_stream(files)))
        counted.writeStream.outputMode("append").format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).select(F.col("w.start").cast("string").alias("s"), "n").collect()
    assert [(r["s"], r["n"]) for r in got] == [("2024-01-02 00:00:00", 1)]


def test_forgetting(spark, tmp_path):
    spark.createDataFrame([(0, 2.0), (0, 4.0), (1, 1.0)], "node int, value double").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("node int, value double").parquet(str(tmp_path / "in"))
    query = incremental.forgetting(stream).writeStream.outputMode("update").format("memory").queryName("forget").start()
    query.processAllAvailable()
    query.stop()
    assert {r["node"]: r["total"] for r in spark.table("forget").collect()} == {0: 6.0, 1: 1.0}
