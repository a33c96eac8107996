"""Streaming ingestion: events become tensor cells, window by window and batch by batch."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from ..functions.bitplan import encode
from ..operators.packed import PackedTensor, TensorShape, merge
from ..sources.tables import read_table
from ..sources.tensors import checkpointed

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def stream_table(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of parquet files as a stream with a time-zoned event time."""
    schema = spark.read.parquet(folder).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling_cells(rows: DataFrame, width: str = "1 hour", late: str | None = None) -> DataFrame:
    """user x type x window counts; with a watermark, cells close once it passes them and later rows are dropped."""
    rows = rows.withWatermark("ts", late) if late else rows
    cells = rows.groupBy(F.window("ts", width), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return cells.select(F.unix_micros("window.start").alias("start"), "user_id", "event_type", "n")


def sliding_cells(rows: DataFrame, width: str = "6 hours", step: str = "3 hours", late: str | None = None) -> DataFrame:
    rows = rows.withWatermark("ts", late) if late else rows
    cells = rows.groupBy(F.window("ts", width, step), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return cells.select(F.unix_micros("window.start").alias("start"), "event_type", "n")


def session_cells(rows: DataFrame, gap: str = "2 hours", late: str | None = None) -> DataFrame:
    """Bursts of one user: events less than the gap apart."""
    rows = rows.withWatermark("ts", late) if late else rows
    cells = rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return cells.select(F.unix_micros("session_window.start").alias("start"), "user_id", "n")


def deduplicated(rows: DataFrame, late: str) -> DataFrame:
    """One row for each event id within the watermark."""
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


class PackedIngest:
    """Merges every micro-batch's packed cells into a base tensor, kept in shared storage between batches.

    A batch that is replayed after a failure is skipped by its number. coords are columns of the
    stream; their lengths are declared, so the plan never changes.
    """

    def __init__(self, base: PackedTensor, coords: list[F.Column], value: F.Column):
        self.base, self.coords, self.value, self.last = base, coords, value, -1

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.last:
            return
        rows = batch.select(*[c.cast("long").alias(f"c{i + 1}") for i, c in enumerate(self.coords)], self.value.cast("double").alias("val")).dropna()
        cells = rows.groupBy(*[f"c{i + 1}" for i in range(len(self.coords))]).agg(F.sum("val").alias("val"))
        delta = self.base.with_df(cells.select(*encode(self.base.plan, [f"c{i + 1}" for i in range(len(self.coords))]), "val"), nnz=None)
        joined = merge(self.base, delta)
        self.base = joined.with_df(checkpointed(joined.df), nnz=None)
        self.last = number

    def start(self, rows: DataFrame, checkpoint: str) -> StreamingQuery:
        return rows.writeStream.foreachBatch(self).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def empty_packed(spark: SparkSession, shape: TensorShape) -> PackedTensor:
    from ..functions.bitplan import BitPlan

    plan = BitPlan.adaptive(shape.lengths)
    schema = ", ".join(f"{c} long" for c in plan.columns) + ", val double"
    return PackedTensor(spark.createDataFrame([], schema), plan, shape)


def _events(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "events", "event_id", "user_id", "event_type", "ts").withColumn("ts", F.col("ts").cast("timestamp"))


# The same window operators on the whole table as a batch, which SQL can express.
QUERIES["stream_tumbling_batch"] = lambda s, d: tumbling_cells(_events(s, d))
ORACLES["stream_tumbling_batch"] = "SELECT epoch_us(date_trunc('hour', ts)) AS start, user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2, 3"
QUERIES["stream_sliding_batch"] = lambda s, d: sliding_cells(_events(s, d))
ORACLES["stream_sliding_batch"] = "SELECT (epoch_us(ts) // 10800000000 - k) * 10800000000 AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY 1, 2"
QUERIES["stream_session_batch"] = lambda s, d: session_cells(_events(s, d))
ORACLES["stream_session_batch"] = "SELECT min(epoch_us(ts)) AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS burst FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, burst"
