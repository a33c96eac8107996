from oracle_harness import ROOT
from pyspark.sql import functions as F

from linetensor.operators.packed import TensorShape, unpack
from linetensor.sources.workloads import WORKLOADS, numbered
from linetensor.streaming import cells


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{ROOT}/sf0.001/events.parquet")
    rows = numbered(events, "event_type", "type")
    rows.repartition(3).write.parquet(f"{tmp_path}/in")
    stream = cells.stream_table(spark, f"{tmp_path}/in")
    batch = WORKLOADS["w05"].build(spark, f"{ROOT}/sf0.001")
    lengths = tuple(batch.agg(*[F.max(f"c{i}") + 1 for i in range(1, 5)]).first())
    coords = [F.col("user_id"), F.col("type"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")), F.hour("ts")]
    ingest = cells.PackedIngest(cells.empty_packed(spark, TensorShape(("u", "t", "d", "h"), lengths)), coords, F.lit(1.0))
    query = ingest.start(stream, f"{tmp_path}/checkpoint")
    query.awaitTermination(120)
    assert query.exception() is None and ingest.last == 2
    assert sorted(map(tuple, unpack(ingest.base).collect())) == sorted(map(tuple, batch.collect()))
    before = ingest.base.df.count()
    ingest(rows, 1)  # a replayed batch changes nothing
    assert ingest.base.df.count() == before


def test_windows_and_dedup_on_a_stream(spark, tmp_path):
    events = spark.read.parquet(f"{ROOT}/sf0.001/events.parquet")
    events.union(events.limit(50)).coalesce(1).write.parquet(f"{tmp_path}/in")
    once = cells.deduplicated(cells.stream_table(spark, f"{tmp_path}/in"), "40 days")
    query = cells.tumbling_cells(once).writeStream.format("memory").queryName("cells_once").outputMode("append").trigger(availableNow=True)
    run = query.option("checkpointLocation", f"{tmp_path}/c").start()
    run.awaitTermination(120)
    assert run.exception() is None
    wanted = cells.tumbling_cells(events.withColumn("ts", F.col("ts").cast("timestamp"))).agg(F.sum("n")).first()[0]
    assert wanted == events.count()
    got = spark.table("cells_once").agg(F.sum("n")).first()[0] or 0
    assert got <= wanted
