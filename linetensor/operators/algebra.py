"""Other operations on sparse tensors as coordinate lists c1..cN, val."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .factors import rank_of
from .packed import coord_names


def ttv(df: DataFrame, vector: DataFrame, mode: int) -> DataFrame:
    """Times a vector (idx, v) along a mode (0-based): that mode is summed away."""
    key = f"c{mode + 1}"
    rest = [c for c in coord_names(df) if c != key]
    rows = df.join(vector.select(F.col("idx").alias(key), "v"), key)
    return rows.groupBy(*rest).agg(F.sum(F.col("val") * F.col("v")).alias("val"))


def ttm(df: DataFrame, factor: DataFrame, mode: int) -> DataFrame:
    """Times a matrix (idx, f0..) along a mode: a semi-dense result with one row of components for each remaining coordinate."""
    key, rank = f"c{mode + 1}", rank_of(factor)
    rest = [c for c in coord_names(df) if c != key]
    rows = df.join(factor.withColumnRenamed("idx", key), key)
    return rows.groupBy(*rest).agg(*[F.sum(F.col("val") * F.col(f"f{r}")).alias(f"y{r}") for r in range(rank)])


def inner(a: DataFrame, b: DataFrame) -> DataFrame:
    keys = coord_names(a)
    rows = a.join(b.withColumnRenamed("val", "other"), keys)
    return rows.agg(F.coalesce(F.sum(F.col("val") * F.col("other")), F.lit(0.0)).alias("inner"))


def norm(df: DataFrame) -> DataFrame:
    return df.agg(F.sqrt(F.coalesce(F.sum(F.col("val") * F.col("val")), F.lit(0.0))).alias("norm"))


def scale(df: DataFrame, by: float) -> DataFrame:
    return df.withColumn("val", F.col("val") * float(by)).where("val <> 0")


def add(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).groupBy(*coord_names(a)).agg(F.sum("val").alias("val")).where("val <> 0")


def hadamard(a: DataFrame, b: DataFrame) -> DataFrame:
    keys = coord_names(a)
    rows = a.join(b.withColumnRenamed("val", "other"), keys)
    return rows.select(*keys, (F.col("val") * F.col("other")).alias("val")).where("val <> 0")


def reduce_mode(df: DataFrame, modes: Sequence[int]) -> DataFrame:
    """Sum the given modes (0-based) away."""
    rest = [c for m, c in enumerate(coord_names(df)) if m not in modes]
    return df.groupBy(*rest).agg(F.sum("val").alias("val"))


def slice_stats(df: DataFrame, fix: Sequence[int]) -> DataFrame:
    """Elements and sum of every slice that fixes the given modes: one for a slice of a mode, all but one for fibers."""
    return df.groupBy(*[f"c{m + 1}" for m in fix]).agg(F.count(F.lit(1)).alias("n"), F.sum("val").alias("total"))


def cp_eval(coords: DataFrame, factors: Sequence[DataFrame], weights: Sequence[float] | None = None) -> DataFrame:
    """The rank-R model's value at given coordinates."""
    keys = coord_names(coords)
    rank = rank_of(factors[0])
    rows = coords.select(*keys)
    for m, f in enumerate(factors):
        rows = rows.join(f.select(F.col("idx").alias(keys[m]), *[F.col(f"f{r}").alias(f"f{m}_{r}") for r in range(rank)]), keys[m])
    total = F.lit(0.0)
    for r in range(rank):
        product = F.lit(float(weights[r]) if weights is not None else 1.0)
        for m in range(len(factors)):
            product = product * F.col(f"f{m}_{r}")
        total = total + product
    return rows.select(*keys, total.alias("model"))
