"""Reading and writing tensors, and cutting lineage through shared storage."""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator, Sequence
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.bitplan import BitPlan
from ..operators.packed import PackedTensor, TensorShape, coord_names, sort_line
from .workloads import COO_TYPES

#: Spark removes the shuffle files of a query when it has ended, and not when the driver collects its garbage.
DROP_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir, or below the warehouse where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"
    return f"{base.rstrip('/')}/tensor-{uuid.uuid4().hex}"


def checkpointed(df: DataFrame) -> DataFrame:
    """The same rows read back from shared storage: nothing before has to be computed again."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def passing(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Gives a checkpointed() for what is not needed beyond the block: its files go at the end, and shuffles as soon as their query has ended."""
    paths, before = [], spark.conf.get(DROP_SHUFFLES)

    def keep(df: DataFrame) -> DataFrame:
        paths.append(shared_folder(spark))
        df.write.parquet(paths[-1])
        return spark.read.schema(df.schema).parquet(paths[-1])

    spark.conf.set(DROP_SHUFFLES, "true")
    try:
        yield keep
    finally:
        spark.conf.set(DROP_SHUFFLES, before)
        for path in paths:
            folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def write_packed(t: PackedTensor, path: str, parts: int | None = None) -> None:
    """Parquet in the order of the position, so that row groups have narrow ranges of p0, and a side-car for the plan."""
    spark = t.df.sparkSession
    sort_line(t, parts).df.select(*t.positions, "val").write.mode("overwrite").parquet(f"{path}/elements")
    side = {"names": t.shape.names, "lengths": t.shape.lengths, "order": t.plan.order, "kind": t.plan.kind, "nnz": t.nnz}
    spark.createDataFrame([(json.dumps(side),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/plan")


def read_packed(spark: SparkSession, path: str) -> PackedTensor:
    side = json.loads(spark.read.text(f"{path}/plan").first()["value"])
    plan = BitPlan(tuple(side["lengths"]), tuple(map(tuple, side["order"])), side["kind"])
    df = spark.read.parquet(f"{path}/elements")
    return PackedTensor(df, plan, TensorShape(tuple(side["names"]), tuple(side["lengths"])), side["nnz"])


def write_tns(df: DataFrame, path: str) -> None:
    """White-space text with coordinates from 1 and the value, the usual exchange form."""
    fields = [(F.col(k) + 1).cast("string") for k in coord_names(df)]
    df.select(F.concat_ws(" ", *fields, F.col("val").cast("string")).alias("value")).write.mode("overwrite").text(path)


def read_tns(spark: SparkSession, path: str, order: int) -> DataFrame:
    """Coordinates from 0 and values; lines that start with # and empty lines are skipped."""
    lines = spark.read.text(path).where("trim(value) <> '' AND NOT startswith(ltrim(value), '#')")
    parts = F.split(F.trim("value"), r"\s+")
    return lines.select(*[(parts.getItem(i).cast("long") - 1).alias(f"c{i + 1}") for i in range(order)], parts.getItem(order).cast("double").alias("val"))


def write_coo(df: DataFrame, path: str, kind: str) -> None:
    df.write.mode("overwrite").format(kind).save(path)


def read_coo(spark: SparkSession, path: str, kind: str, order: int) -> DataFrame:
    """csv, json, orc or parquet with an explicit schema."""
    return spark.read.schema(COO_TYPES[order]).format(kind).load(path)


def register_views(spark: SparkSession, name: str, coo: DataFrame, t: PackedTensor, factors: Sequence[DataFrame]) -> None:
    """coo_<name>, packed_<name> and factor_<name>_<mode> for SQL."""
    coo.createOrReplaceTempView(f"coo_{name}")
    t.df.createOrReplaceTempView(f"packed_{name}")
    for m, f in enumerate(factors, 1):
        f.createOrReplaceTempView(f"factor_{name}_{m}")
