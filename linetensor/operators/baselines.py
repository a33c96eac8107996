"""The formats that the packed tensor is compared with, and their kernels.

Coordinate list with and without private outputs, the block format with its superblocks and waves,
fiber trees (one copy for each root, tiled or not, with kernels for the root and for other modes),
and row pointers for matrices. All take a coordinate list c1..cN, val with distinct coordinates.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bitplan import BitPlan, encode
from ..plans.choose import listable
from .factors import rank_of
from .kernels import _products, _sums
from .packed import coord_names

BLOCK_BITS = 7


def _contributions(df: DataFrame, factors: Sequence[DataFrame], mode: int, lengths: Sequence[int], keep: Sequence[str], delivery: str = "auto") -> DataFrame:
    rows = df.withColumnRenamed(f"c{mode + 1}", "idx")
    return _products(rows, factors, mode, lengths, delivery, [*keep, "idx"])


def coo_kr(df: DataFrame, factors: Sequence[DataFrame], mode: int, lengths: Sequence[int], private: bool = False) -> DataFrame:
    """Coordinate list: elements go to the owner of their row, or every task keeps its own output that is then reduced."""
    rank = rank_of(factors[mode])
    if not private:
        return _contributions(df.repartition(f"c{mode + 1}"), factors, mode, lengths, []).groupBy("idx").agg(*_sums(rank))
    own = df.withColumn("task", F.spark_partition_id())
    partial = _contributions(own, factors, mode, lengths, ["task"]).groupBy("task", "idx").agg(*_sums(rank))
    return partial.groupBy("idx").agg(*_sums(rank))


def coo_reorder_morton(df: DataFrame, lengths: Sequence[int]) -> DataFrame:
    """The fractal curve as an order only: the coordinate list sorted by it, with no packed index kept."""
    plan = BitPlan.morton(lengths)
    keyed = df.withColumns({f"__{n}": c for n, c in zip(plan.columns, encode(plan, coord_names(df)), strict=True)})
    by = [f"__{n}" for n in plan.columns]
    return keyed.repartitionByRange(*by).sortWithinPartitions(*by).drop(*by)


@dataclass
class BlockTensor:
    """elements: block base bK, one-byte offsets oK and val; superblocks are runs of blocks."""

    elements: DataFrame
    lengths: tuple[int, ...]
    block_bits: int
    super_bits: int


def blk_build(df: DataFrame, lengths: Sequence[int], block_bits: int = BLOCK_BITS, super_bits: int = 10) -> BlockTensor:
    keys = coord_names(df)
    mask = F.lit((1 << block_bits) - 1).cast("long")
    bases = [F.shiftright(k, block_bits).alias(f"b{i + 1}") for i, k in enumerate(keys)]
    offsets = [F.col(k).bitwiseAND(mask).cast("short").alias(f"o{i + 1}") for i, k in enumerate(keys)]
    by = [f"b{i + 1}" for i in range(len(keys))]
    clustered = df.select(*bases, *offsets, "val").repartition(*by).sortWithinPartitions(*by)
    return BlockTensor(clustered, tuple(lengths), block_bits, super_bits)


def blk_blocks(t: BlockTensor) -> DataFrame:
    """Blocks with their number of elements and superblock."""
    n = len(t.lengths)
    step = t.super_bits - t.block_bits
    supers = [F.shiftright(f"b{i + 1}", step).alias(f"s{i + 1}") for i in range(n)]
    return t.elements.groupBy(*[f"b{i + 1}" for i in range(n)]).agg(F.count(F.lit(1)).alias("n")).select("*", *supers)


def blk_waves(t: BlockTensor, mode: int) -> DataFrame:
    """Superblocks with the wave in which each may run: those of one wave never share an output superblock of the mode."""
    supers = [f"s{i + 1}" for i in range(len(t.lengths))]
    sizes = blk_blocks(t).groupBy(*supers).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("blocks"))
    return sizes.withColumn("wave", F.row_number().over(Window.partitionBy(f"s{mode + 1}").orderBy(*supers)))


def blk_counts(t: BlockTensor) -> tuple[int, int]:
    """Number of blocks and of superblocks."""
    row = blk_blocks(t).agg(F.count(F.lit(1)).alias("b"), F.count_distinct(*[f"s{i + 1}" for i in range(len(t.lengths))]).alias("s")).first()
    return row["b"], row["s"]


def blk_kr(t: BlockTensor, factors: Sequence[DataFrame], mode: int) -> DataFrame:
    """Sums inside each block, then over the blocks of a superblock, then over superblocks."""
    n, rank = len(t.lengths), rank_of(factors[mode])
    coords = [(F.shiftleft(f"b{i + 1}", t.block_bits) + F.col(f"o{i + 1}")).alias(f"c{i + 1}") for i in range(n)]
    base = [f"b{i + 1}" for i in range(n)]
    rows = _contributions(t.elements.select(*base, *coords, "val"), factors, mode, t.lengths, base)
    inside = rows.groupBy(*base, "idx").agg(*_sums(rank))
    step = t.super_bits - t.block_bits
    supers = [F.shiftright(b, step).alias(f"s{i + 1}") for i, b in enumerate(base)]
    wider = inside.select(*supers, "idx", *[f"y{r}" for r in range(rank)]).groupBy(*[f"s{i + 1}" for i in range(n)], "idx").agg(*_sums(rank))
    return wider.groupBy("idx").agg(*_sums(rank))


@dataclass
class FiberTree:
    """levels: modes from the root down (0-based); prefixes of coordinates are the nodes. A tile is a leading key."""

    df: DataFrame
    levels: tuple[int, ...]
    lengths: tuple[int, ...]
    tile: int | None = None


def tree_levels(lengths: Sequence[int], root: int) -> tuple[int, ...]:
    """Root first, the others by increasing length, so that prefixes are shared as much as possible."""
    return (root, *sorted((m for m in range(len(lengths)) if m != root), key=lambda m: (lengths[m], m)))


def csf_build(df: DataFrame, lengths: Sequence[int], root: int, tile: int | None = None) -> FiberTree:
    """One tree: elements sorted by their path. With a tile, ranges of that many root indices lead the path."""
    levels = tree_levels(lengths, root)
    by = [f"c{m + 1}" for m in levels]
    rows = df
    if tile:
        last = levels[-1]
        rows, by = df.withColumn("tile", F.floor(F.col(f"c{last + 1}") / tile)), ["tile", *by]
    return FiberTree(rows.repartition(f"c{root + 1}").sortWithinPartitions(*by), levels, tuple(lengths), tile)


def csf_build_all(df: DataFrame, lengths: Sequence[int], tile: int | None = None) -> list[FiberTree]:
    return [csf_build(df, lengths, m, tile) for m in range(len(lengths))]


def _paths(t: FiberTree) -> list[str]:
    return [*(["tile"] if t.tile else []), *[f"c{m + 1}" for m in t.levels]]


def csf_nodes(t: FiberTree) -> DataFrame:
    """(level, nodes): distinct prefixes of each level, root first."""
    path = _paths(t)
    parts = [t.df.select(*path[: k + 1]).distinct().agg(F.count(F.lit(1)).alias("nodes")).select(F.lit(k).cast("long").alias("level"), "nodes") for k in range(len(path))]
    return reduce(DataFrame.unionByName, parts)


def csf_level(t: FiberTree, level: int) -> DataFrame:
    """Node ids of a level with the number of children each holds: the level's id and pointer arrays as rows."""
    path = _paths(t)[: level + 2]
    below = t.df.select(*path).distinct()
    return below.groupBy(*path[: level + 1]).agg(F.count(F.lit(1)).alias("children"))


def csf_kr(t: FiberTree, factors: Sequence[DataFrame], mode: int) -> DataFrame:
    """The kernel of a tree: sums from the leaves upward, each multiplied once by its parent's factor row.

    For the root mode every level is one smaller aggregate. For another mode, the sums below its
    level are gathered the same way, the factor rows above are multiplied in, and rows of one index
    from different branches are merged at the end, which costs what a tree of its own would save.
    """
    rank = rank_of(factors[mode])
    at = t.levels.index(mode)
    lead = ["tile"] if t.tile else []
    ys = [f"y{r}" for r in range(rank)]

    def times(rows: DataFrame, m: int) -> DataFrame:
        side = factors[m].select(F.col("idx").alias(f"c{m + 1}"), *[f"f{r}" for r in range(rank)])
        side = F.broadcast(side) if listable(t.lengths[m], rank) else side
        held = [c for c in rows.columns if c not in ys and c != f"c{m + 1}"]
        return rows.join(side, f"c{m + 1}").select(*held, *([f"c{m + 1}"] if m in t.levels[:at] else []), *[(F.col(y) * F.col(f"f{r}")).alias(y) for r, y in enumerate(ys)])

    rows = t.df.select(*_paths(t), *[F.col("val").alias(y) for y in ys])
    for k in range(len(t.levels) - 1, at, -1):
        rows = times(rows, t.levels[k])
        rows = rows.groupBy(*lead, *[f"c{m + 1}" for m in t.levels[:k]]).agg(*_sums(rank))
    for m in t.levels[:at]:
        rows = times(rows, m)
    return rows.groupBy(F.col(f"c{mode + 1}").alias("idx")).agg(*_sums(rank))


def csr_build(df: DataFrame) -> DataFrame:
    """Row pointers of a matrix: each row with its count and its columns and values in order."""
    cells = F.sort_array(F.collect_list(F.struct("c2", "val")))
    return df.groupBy("c1").agg(F.count(F.lit(1)).alias("n"), cells.alias("cells"))
