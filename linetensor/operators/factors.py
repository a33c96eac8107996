"""Factor matrices: deterministic values, layouts, small dense algebra."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

RANK = 16


def factor_value(mode: int, idx: Column, r: Column | int, denominator: int) -> Column:
    """The deterministic entry of a factor: a fraction with a power of two below it, so that sums are exact."""
    step = F.lit(r) if isinstance(r, int) else r
    return ((idx * 31 + step * 17 + mode * 7) % denominator).cast("double") / float(denominator)


def factor_sql(mode: int, idx: str, r: int | str, denominator: int) -> str:
    return f"((({idx} * 31 + {r} * 17 + {mode * 7}) % {denominator})::DOUBLE / {denominator})"


def _indices(spark: SparkSession, length: int, indices: DataFrame | None) -> DataFrame:
    """Every index of a mode, or only the given ones (idx), for modes too long to be listed."""
    return spark.range(length).withColumnRenamed("id", "idx") if indices is None else indices.select("idx")


def init_factor(spark: SparkSession, length: int, rank: int, mode: int, denominator: int = 64, indices: DataFrame | None = None) -> DataFrame:
    """(idx, f0..f{R-1}), computed row by row from the index; a row depends on its index alone."""
    rows = _indices(spark, length, indices)
    return rows.select("idx", *[factor_value(mode, F.col("idx"), r, denominator).alias(f"f{r}") for r in range(rank)])


def init_factors(spark: SparkSession, lengths: Sequence[int], rank: int = RANK, denominator: int = 64) -> list[DataFrame]:
    return [init_factor(spark, n, rank, m, denominator) for m, n in enumerate(lengths)]


def seeded_factor(spark: SparkSession, length: int, rank: int, mode: int, seed: int, indices: DataFrame | None = None) -> DataFrame:
    """Start values spread by a hash of (seed, mode, index, component), the same in every run."""
    rows = _indices(spark, length, indices)
    value = lambda r: (F.pmod(F.xxhash64(F.lit(seed), F.lit(mode), F.col("idx"), F.lit(r)), F.lit(1 << 20)).cast("double") + 0.5) / float(1 << 20)
    return rows.select("idx", *[value(r).alias(f"f{r}") for r in range(rank)])


def rank_of(factor: DataFrame) -> int:
    return sum(c[0] == "f" and c[1:].isdigit() for c in factor.columns)


def to_array(factor: DataFrame) -> DataFrame:
    return factor.select("idx", F.array(*[f"f{r}" for r in range(rank_of(factor))]).alias("row"))


def to_long(factor: DataFrame) -> DataFrame:
    return to_array(factor).select("idx", F.posexplode("row").alias("r", "v"))


def from_long(factor: DataFrame, rank: int) -> DataFrame:
    """Back to columns; missing entries are zero."""
    return factor.groupBy("idx").agg(*[F.coalesce(F.sum(F.when(F.col("r") == r, F.col("v"))), F.lit(0.0)).alias(f"f{r}") for r in range(rank)])


def from_numpy(spark: SparkSession, values: np.ndarray) -> DataFrame:
    rows = [(i, *map(float, row)) for i, row in enumerate(values)]
    return spark.createDataFrame(rows, "idx long, " + ", ".join(f"f{r} double" for r in range(values.shape[1])))


def gram(factor: DataFrame) -> np.ndarray:
    """R x R products of columns: one aggregate row of R(R+1)/2 sums goes to the driver."""
    rank = rank_of(factor)
    pairs = [(i, j) for i in range(rank) for j in range(i, rank)]
    row = factor.agg(*[F.sum(F.col(f"f{i}") * F.col(f"f{j}")).alias(f"g{i}_{j}") for i, j in pairs]).first()
    out = np.zeros((rank, rank))
    for (i, j), v in zip(pairs, row, strict=True):
        out[i, j] = out[j, i] = v or 0.0
    return out


def times_matrix(factor: DataFrame, matrix: np.ndarray, source: str = "f") -> DataFrame:
    """Each row times a small matrix, whose entries are literals of the plan."""
    columns = []
    for j in range(matrix.shape[1]):
        total = F.lit(0.0)
        for i in range(matrix.shape[0]):
            total = total + F.col(f"{source}{i}") * float(matrix[i, j])
        columns.append(total.alias(f"f{j}"))
    return factor.select("idx", *columns)


def column_norms(factor: DataFrame, norm: str = "l2") -> np.ndarray:
    rank = rank_of(factor)
    each = {"l2": lambda c: F.sqrt(F.sum(c * c)), "max": lambda c: F.max(F.abs(c))}[norm]
    row = factor.agg(*[each(F.col(f"f{r}")).alias(f"n{r}") for r in range(rank)]).first()
    return np.array([v or 0.0 for v in row])


def normalise(factor: DataFrame, norm: str = "l2") -> tuple[DataFrame, np.ndarray]:
    """Columns scaled to norm one, and their norms; a column of zeros stays."""
    size = column_norms(factor, norm)
    scale = [float(1 / s) if s else 1.0 for s in size]
    return factor.select("idx", *[(F.col(f"f{r}") * k).alias(f"f{r}") for r, k in enumerate(scale)]), size


def khatri_rao(b: DataFrame, c: DataFrame, length: int | None = None) -> DataFrame:
    """All pairs of rows multiplied component by component; row j * K + k. For small factors only: kernels never form it.

    length: K, where c lacks rows of its mode.
    """
    rank, length = rank_of(b), c.count() if length is None else length
    pairs = b.alias("b").crossJoin(c.alias("c"))
    return pairs.select((F.col("b.idx") * length + F.col("c.idx")).alias("idx"), *[(F.col(f"b.f{r}") * F.col(f"c.f{r}")).alias(f"f{r}") for r in range(rank)])
