"""Plumbing shared by the training-data operators."""

from __future__ import annotations

import uuid
import weakref
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows and bytes of one Arrow batch; they bound a Python worker's memory, not what is computed.
BATCH_ROWS, BATCH_BYTES = 256, 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """One of the given tables, pruned to the named columns."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def small_batches(spark: SparkSession, rows: int = BATCH_ROWS) -> None:
    """Keep Arrow batches small, as texts may be very long. These settings may change at run time."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def arrow_map(df: DataFrame, function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """mapInArrow with bounded batches."""
    small_batches(df.sparkSession)
    return df.mapInArrow(function, schema)


def rows_out(rows: Iterable[tuple], schema: pa.Schema, limit: int = 2048, most: int = BATCH_BYTES, weigh: Callable[[tuple], int] | None = None) -> Iterator[pa.RecordBatch]:
    """Gather row tuples into record batches of bounded rows and bytes."""
    held: list[tuple] = []
    size = 0
    for row in rows:
        held.append(row)
        if weigh:
            size += weigh(row)
        if len(held) >= limit or size >= most:
            yield _batch(held, schema)
            held, size = [], 0
    if held:
        yield _batch(held, schema)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def pairs_of(batch: pa.RecordBatch, key: str, text: str) -> Iterator[tuple]:
    """(key, text) of each row; a null text reads as None."""
    return zip(batch.column(key).to_pylist(), batch.column(text).to_pylist(), strict=True)


def shared_folder(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir, which every executor can reach."""
    base = spark.conf.get("spark.checkpoint.dir", None) or _own_folder(spark)
    return f"{base.rstrip('/')}/linetensor-{uuid.uuid4().hex}"


def _own_folder(spark: SparkSession) -> str:
    """Where the session names no checkpoint folder: one below the warehouse, which is shared as well."""
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"


def written(df: DataFrame, most: int | None = None) -> DataFrame:
    """Cut the lineage: write to the shared folder and read again, so that a lost executor costs no recomputation.

    most: how many tasks are enough for it, from a count of rows, so that small tables are not strewn over many files.
    """
    path = shared_folder(df.sparkSession)
    df = df.coalesce(most) if most else df
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    _FOLDERS[id(out)] = (weakref.ref(out), path)
    return out


#: Where written tables lie, by the frame that reads them.
_FOLDERS: dict[int, tuple[weakref.ref, str]] = {}


def discard(*tables: DataFrame) -> None:
    """Remove the folders of written tables that nothing reads any more: what came of them is written as well."""
    for df in tables:
        held = _FOLDERS.pop(id(df), None)
        if held and held[0]() is df:
            jvm = df.sparkSession.sparkContext._jvm
            path = jvm.org.apache.hadoop.fs.Path(held[1])
            path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def sha(column) -> "F.Column":
    return F.sha2(F.encode(column, "UTF-8"), 256)
