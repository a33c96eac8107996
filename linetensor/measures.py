"""Cost and accuracy measures: sizes, reuse, balance, conflicts, bounds and comparisons."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.bitplan import BitPlan, decode, ideal_bits, mode_bits
from .operators.baselines import tree_levels
from .operators.combinations import combination_counts
from .operators.packed import PackedTensor, coord_names
from .plans.choose import fiber_reuse

BLOCK_BITS = 7


def _whole(bits: float, word: int) -> int:
    return math.ceil(bits / word) * word


def mask_bits(lengths: Sequence[int]) -> int:
    return sum(mode_bits(lengths))


def packed_bits(lengths: Sequence[int], nnz: int, word: int | None = None) -> int:
    """Index bits of the packed format, each position filled up to whole words if a word is given."""
    bits = mask_bits(lengths)
    return nnz * (_whole(bits, word) if word else bits)


def coo_bits(lengths: Sequence[int], nnz: int, word: int) -> int:
    return nnz * sum(_whole(b, word) for b in mode_bits(lengths))


def metadata_ratio(lengths: Sequence[int], word: int = 64) -> float:
    """Index bits of a coordinate list over those of the packed format, at a word size; one at least."""
    packed = packed_bits(lengths, 1, word)
    return coo_bits(lengths, 1, word) / packed if packed else 1.0


def morton_bits(lengths: Sequence[int]) -> int:
    return BitPlan.morton(lengths).bits


def line_factor(lengths: Sequence[int]) -> float:
    """How many times longer the fractal curve is than the packed line."""
    return 2.0 ** (morton_bits(lengths) - mask_bits(lengths))


def density(lengths: Sequence[int], nnz: int) -> float:
    return nnz / math.prod(float(n) for n in lengths)


def coo_bytes(order: int, nnz: int) -> int:
    return nnz * (8 * order + 8)


def packed_bytes(lengths: Sequence[int], nnz: int) -> int:
    return nnz * (8 * max(1, math.ceil(mask_bits(lengths) / 64)) + 8)


def side_bytes(order: int, limbs: int, segments: int) -> int:
    """Masks and segment boxes, which are shared by all elements."""
    return 8 * order * limbs + segments * (16 * order + 16)


def block_bytes(order: int, nnz: int, blocks: int, superblocks: int) -> int:
    return nnz * (order + 8) + blocks * (4 * order + 8) + superblocks * 8


def tree_bytes(nodes: Sequence[int], nnz: int) -> int:
    """One fiber tree from its node counts, root first: an id for each node, pointers of inner levels, values."""
    return sum(8 * n for n in nodes) + sum(8 * (n + 1) for n in nodes[:-1]) + 8 * nnz


def distinct_counts(df: DataFrame, sets: Sequence[tuple[str, ...]]) -> dict[tuple[str, ...], int]:
    """How many distinct combinations each set of columns has: one pass with grouping sets for all of them."""
    sets = sorted({tuple(sorted(s)) for s in sets})
    columns = sorted({c for s in sets for c in s})
    grouped = df.groupingSets([[F.col(c) for c in s] for s in sets], *columns).agg(F.grouping_id().alias("without"))
    found = {r["without"]: r["n"] for r in grouped.groupBy("without").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each set
    left_out = lambda s: sum(1 << (len(columns) - 1 - i) for i, c in enumerate(columns) if c not in s)
    return {s: found.get(left_out(s), 0) for s in sets}


def storage_bytes(df: DataFrame, lengths: Sequence[int], tile: int = 64, by: Sequence[int] | None = None) -> dict[str, int]:
    """Bytes of every format with values, from a coordinate list with distinct rows.

    by: declared numbers, in whose order the modes make the levels of trees; without them the lengths order them.
    """
    divisors = {"c": 1, "t": tile, "b": 1 << 7, "s": 1 << 10, "u": 1 << 14}
    part = lambda name: (int(name[1:]) - 1, divisors[name[0]])

    def counts_of(sets: Sequence[tuple[str, ...]]) -> dict[tuple[str, ...], int]:
        sets = sorted({tuple(sorted(s)) for s in sets})
        return dict(zip(sets, combination_counts(df, [tuple(map(part, s)) for s in sets], lengths), strict=True))

    return storage_model(counts_of, lengths, by)


def storage_model(counts_of: Callable[[Sequence[tuple[str, ...]]], dict[tuple[str, ...], int]], lengths: Sequence[int], by: Sequence[int] | None = None) -> dict[str, int]:
    """Bytes of every format from the numbers of distinct combinations of coordinates (c), tiles (t) and blocks (b, s, u)."""
    n, modes = len(lengths), range(len(lengths))
    levels = {root: tree_levels(by or lengths, root) for root in modes}
    paths = {root: tuple(f"c{m + 1}" for m in levels[root]) for root in modes}
    tiled = {root: (f"t{levels[root][-1] + 1}", *path) for root, path in paths.items()}
    blocks = {name: tuple(f"{name}{m + 1}" for m in modes) for name in "bsu"}
    prefixes = [p[: k + 1] for p in (*paths.values(), *tiled.values()) for k in range(len(p))]
    counts = counts_of([*prefixes, *blocks.values()])
    count = lambda s: counts[tuple(sorted(s))]
    nnz = count(paths[0])
    trees = lambda of: sum(tree_bytes([count(p[: k + 1]) for k in range(len(p))], nnz) for p in of.values())
    return {
        "coo": coo_bytes(n, nnz),
        "packed": packed_bytes(lengths, nnz),
        "blk10": block_bytes(n, nnz, count(blocks["b"]), count(blocks["s"])),
        "blk14": block_bytes(n, nnz, count(blocks["b"]), count(blocks["u"])),
        "csf": trees(paths),
        "csf_tile": trees(tiled),
    }


def geomean(column: str | Column) -> Column:
    """Geometric mean of the positive values of a column; others, such as runs that failed, are left out."""
    c = F.col(column) if isinstance(column, str) else column
    return F.exp(F.avg(F.when(c > 0, F.ln(c))))


def block_counts(df: DataFrame, bits: int = BLOCK_BITS) -> DataFrame:
    """Elements of each block of 2^bits in every mode, of a coordinate list."""
    keys = [F.shiftright(k, bits).alias(f"b{i + 1}") for i, k in enumerate(coord_names(df))]
    return df.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))


def block_stats(df: DataFrame, bits: int = BLOCK_BITS) -> DataFrame:
    """Number of blocks and the least, quartiles, greatest and mean of their elements."""
    quartiles = [F.percentile("n", F.lit(q)).alias(name) for name, q in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))]
    return block_counts(df, bits).agg(F.count(F.lit(1)).alias("blocks"), F.min("n").alias("least"), *quartiles, F.max("n").alias("most"), F.avg("n").alias("mean"))


def imbalance(df: DataFrame, *by: str) -> DataFrame:
    """Greatest count of a group over the mean count."""
    sizes = df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(F.count(F.lit(1)).alias("parts"), F.max("n").alias("most"), F.avg("n").alias("mean"), (F.max("n") / F.avg("n")).alias("imbalance"))


def conflict_stats(t: PackedTensor, mode: int) -> DataFrame:
    """Of one mode (0-based): output rows, rows that several segments touch, partial rows, and elements in shared rows."""
    cells = t.df.select("seg", decode(t.plan, mode).alias("idx")).groupBy("idx", "seg").agg(F.count(F.lit(1)).alias("n"))
    rows = cells.groupBy("idx").agg(F.count(F.lit(1)).alias("segments"), F.sum("n").alias("n"))
    shared = F.col("segments") > 1
    return rows.agg(
        F.count(F.lit(1)).alias("rows_touched"),
        F.sum(shared.cast("long")).alias("rows_shared"),
        F.sum("segments").alias("partial_rows"),
        F.sum(F.when(shared, F.col("n")).otherwise(0)).alias("elements_shared"),
    )


def staging_bytes(boxes: DataFrame, mode: int, rank: int) -> DataFrame:
    """Width of all segments' intervals of a mode, and the doubles that dense staging would take (mode 1-based)."""
    width = F.sum(F.col(f"hi{mode}") - F.col(f"lo{mode}") + 1)
    return boxes.agg(width.alias("width"), (width * (8 * rank)).alias("bytes"))


def speedup(base_seconds: float, seconds: float) -> float | None:
    return base_seconds / seconds if base_seconds and seconds else None


def efficiency(gain: float, cores: int) -> float:
    return gain / cores


def mode_variation(seconds: Sequence[float]) -> float:
    return max(seconds) / min(seconds)


def comparison_model(nnz: int, keys: int) -> float:
    """Key comparisons of a sort: elements times levels times columns compared."""
    return nnz * math.log2(max(nnz, 2)) * keys


def kernel_work(nnz: int, order: int, rank: int, limbs: int, rows_out: int) -> tuple[int, int]:
    """Operations and bytes of one kernel: products and one sum for each component; index, value, factor rows and output."""
    flops = nnz * rank * order
    moved = nnz * (8 * limbs + 8 + (order - 1) * rank * 8) + rows_out * rank * 8
    return flops, moved


def roofline(peak: float, bandwidth: float, flops: float, moved: float) -> float:
    """Attainable operations a second for this mix of work and traffic."""
    return min(peak, bandwidth * flops / moved)


def peak_flops(n: int = 1024) -> float:
    """Operations a second of a dense product of doubles on this machine, on the cores that NumPy takes."""
    a = np.ones((n, n))
    a @ a
    start = time.perf_counter()
    a @ a
    return 2 * n**3 / (time.perf_counter() - start)


def attempt(run: Callable[[], float]) -> tuple[float | None, str]:
    """Seconds of a run and ``ok``, or no seconds and why: ``oom`` where memory ran out, else ``error``. One failing format does not end a comparison."""
    try:
        return run(), "ok"
    except Exception as wrong:  # noqa: BLE001
        said = str(wrong).lower()
        return None, "oom" if isinstance(wrong, MemoryError) or "outofmemory" in said or "heap space" in said else "error"


def stream_bandwidth(megabytes: int = 64) -> float:
    """Bytes a second of a NumPy triad on this machine, on one core."""
    n = megabytes << 17
    a, b, c = np.zeros(n), np.ones(n), np.ones(n)
    start = time.perf_counter()
    np.multiply(c, 3.0, out=a)
    np.add(a, b, out=a)
    return 5 * 8 * n / (time.perf_counter() - start)


def timed(run: Callable[[], DataFrame], warmup: int = 1, runs: int = 3) -> list[float]:
    """Seconds of each run into the noop sink, after the warm-up."""
    out = []
    for k in range(warmup + runs):
        start = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if k >= warmup:
            out.append(time.perf_counter() - start)
    return out


def compare_factors(a: DataFrame, b: DataFrame) -> float:
    """Greatest difference of entries of two factors."""
    columns = [c for c in a.columns if c != "idx"]
    both = a.alias("a").join(b.alias("b"), "idx", "full")
    worst = F.greatest(*[F.abs(F.coalesce(F.col(f"a.{c}"), F.lit(0.0)) - F.coalesce(F.col(f"b.{c}"), F.lit(0.0))) for c in columns], F.lit(0.0))
    return both.agg(F.max(worst)).first()[0] or 0.0


def oracle_best(results: DataFrame, by: str = "workload", value: str = "seconds") -> DataFrame:
    """For each tensor and family of formats the variant with the least value; runs that failed are null and lose."""
    return results.where(F.col(value).isNotNull()).groupBy(by, "family").agg(F.min(value).alias("best"), F.min_by("variant", value).alias("variant"))


def profile(lengths: Sequence[int], nnz: int) -> dict[str, float]:
    """Formula measures of a tensor."""
    return {
        "nnz": float(nnz),
        "mask_bits": float(mask_bits(lengths)),
        "ideal_bits": ideal_bits(lengths),
        "morton_bits": float(morton_bits(lengths)),
        "line_factor": line_factor(lengths),
        "metadata_ratio_64": metadata_ratio(lengths, 64),
        "metadata_ratio_8": metadata_ratio(lengths, 8),
        "density": density(lengths, nnz),
        "worst_reuse": min(fiber_reuse(nnz, n) for n in lengths),
        "coo_bytes": float(coo_bytes(len(lengths), nnz)),
        "packed_bytes": float(packed_bytes(lengths, nnz)),
    }
