"""The packed tensor: one position and one value for each non-zero, in the order of the position."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bitplan import LIMB_BITS, BitPlan, decode, decode_all, encode

#: Top position bits by which ranks are counted: the table of counts has at most two to that power rows.
RANK_BITS = 12
#: Cells of a mode by which rows find runs of shared indices.
COVER_CELLS = 1024
#: Boxes up to this number are broadcast.
SMALL_BOXES = 1 << 16


@dataclass
class TensorShape:
    names: tuple[str, ...]
    lengths: tuple[int, ...]

    @property
    def order(self) -> int:
        return len(self.lengths)


@dataclass
class PackedTensor:
    """df has the limbs p0, p1, … and val, and ``seg`` and ``rnk`` once it is cut in segments."""

    df: DataFrame
    plan: BitPlan
    shape: TensorShape
    nnz: int | None = None
    segments: int | None = None
    boxes: DataFrame | None = field(default=None, repr=False)

    def count(self) -> int:
        """Number of non-zeros; counted once."""
        if self.nnz is None:
            self.nnz = self.df.count()
        return self.nnz

    @property
    def positions(self) -> list[str]:
        return self.plan.columns

    def with_df(self, df: DataFrame, **changes) -> PackedTensor:
        return PackedTensor(df, self.plan, self.shape, **{"nnz": self.nnz, "segments": self.segments, "boxes": self.boxes, **changes})

    def coords(self, *modes: int) -> list[Column]:
        return [decode(self.plan, m) for m in (modes or range(self.shape.order))]


def coord_names(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c[0] == "c" and c[1:].isdigit()]


def infer_shape(df: DataFrame, names: Sequence[str] | None = None) -> TensorShape:
    """Mode lengths as the greatest coordinate plus one: one aggregate of one row."""
    keys = coord_names(df)
    top = df.agg(*[F.max(k).alias(k) for k in keys]).first()
    return TensorShape(tuple(names or keys), tuple((top[k] if top[k] is not None else 0) + 1 for k in keys))


def pack(df: DataFrame, shape: TensorShape | None = None, plan: BitPlan | None = None, names: Sequence[str] | None = None, impl: str = "tables") -> PackedTensor:
    """Pack coordinates c1..cN with distinct rows. A declared shape saves the pass that looks for it."""
    shape = shape or infer_shape(df, names)
    plan = plan or BitPlan.adaptive(shape.lengths)
    rows = df.select(*encode(plan, coord_names(df), impl), "val")
    return PackedTensor(rows, plan, shape)


def unpack(t: PackedTensor) -> DataFrame:
    return t.df.select(*decode_all(t.plan), "val")


def sort_line(t: PackedTensor, parts: int | None = None) -> PackedTensor:
    """Range partitions along the line, sorted inside: the order in which the tensor is stored."""
    by = t.positions
    df = t.df.repartitionByRange(parts, *by) if parts else t.df.repartitionByRange(*by)
    return t.with_df(df.sortWithinPartitions(*by))


def _top(plan: BitPlan, bits: int) -> Column:
    """The top bits of a position as one number; bits is at most what the first limb holds."""
    width = plan.bits - (plan.limbs - 1) * LIMB_BITS
    return F.shiftright("p0", max(0, width - bits)).cast("long")


def prefix_partition(t: PackedTensor, bits: int) -> DataFrame:
    """(prefix, n): sub-spaces by the top bits of the position. They do not overlap, but are as uneven as the data."""
    return t.df.groupBy(_top(t.plan, bits).alias("prefix")).agg(F.count(F.lit(1)).alias("n"))


def ranked(t: PackedTensor, bits: int = RANK_BITS) -> DataFrame:
    """df with ``rnk``, the exact place of each element along the line, from 0.

    Elements are counted by the top bits of their position; a rank is the count of all lower
    prefixes and the place inside the prefix. Every prefix is its own sort, so no task sees all.
    """
    counts = sorted((r["prefix"], r["n"]) for r in prefix_partition(t, bits).collect())  # at most 2^bits rows
    before, rows = 0, []
    for prefix, n in counts:
        rows.append((prefix, before))
        before += n
    t.nnz = before
    shifts = t.df.sparkSession.createDataFrame(rows, "prefix long, before long")
    inside = F.row_number().over(Window.partitionBy("prefix").orderBy(*t.positions)) - 1
    df = t.df.withColumn("prefix", _top(t.plan, bits)).join(F.broadcast(shifts), "prefix")
    return df.withColumn("rnk", F.col("before") + inside).drop("prefix", "before")


def segment(t: PackedTensor, segments: int, bits: int = RANK_BITS) -> PackedTensor:
    """Cut the line in segments whose counts differ by one at most, and record each segment's box of mode intervals."""
    df = ranked(t, bits)
    size, extra = divmod(t.nnz, segments)
    cut = extra * (size + 1)
    seg = F.when(F.col("rnk") < cut, F.floor(F.col("rnk") / (size + 1)))
    seg = seg.otherwise(extra + F.floor((F.col("rnk") - cut) / size)) if size else seg
    out = t.with_df(df.withColumn("seg", seg.cast("long")), segments=segments)
    out.boxes = boxes(out)
    return out


def dealt(t: PackedTensor) -> PackedTensor:
    """One task for each segment: segment numbers are partition numbers."""
    # the partition number is a column of its own, so that groups of it need no second exchange
    return t.with_df(t.df.withColumn("seg", F.col("seg").cast("int")).repartitionById(t.segments, "seg"))


def boxes(t: PackedTensor) -> DataFrame:
    """For each segment its count, first and last position, and the interval of every mode."""
    rows = t.df.select("seg", F.struct(*t.positions).alias("p"), *decode_all(t.plan))
    modes = range(1, t.shape.order + 1)
    spans = [x for m in modes for x in (F.min(f"c{m}").alias(f"lo{m}"), F.max(f"c{m}").alias(f"hi{m}"))]
    out = rows.groupBy("seg").agg(F.count(F.lit(1)).alias("n"), F.min("p").alias("a"), F.max("p").alias("b"), *spans)
    ends = [F.col(f"{x}.{p}").alias(f"{p}_{y}") for x, y in (("a", "min"), ("b", "max")) for p in t.positions]
    return out.select("seg", "n", *ends, *[f"{x}{m}" for m in modes for x in ("lo", "hi")])


def box_overlaps(b: DataFrame, order: int) -> DataFrame:
    """For each pair of segments whose boxes share space in every mode: the shared extent of each mode."""
    x, y = b.alias("x"), F.broadcast(b).alias("y") if b.limit(SMALL_BOXES + 1).count() <= SMALL_BOXES else b.alias("y")
    meet = F.col("x.seg") < F.col("y.seg")
    for m in range(1, order + 1):
        meet = meet & (F.col(f"x.lo{m}") <= F.col(f"y.hi{m}")) & (F.col(f"y.lo{m}") <= F.col(f"x.hi{m}"))
    shared = [(F.least(f"x.hi{m}", f"y.hi{m}") - F.greatest(f"x.lo{m}", f"y.lo{m}") + 1).alias(f"shared{m}") for m in range(1, order + 1)]
    return x.join(y, meet).select(F.col("x.seg").alias("seg_a"), F.col("y.seg").alias("seg_b"), *shared)


def coverage(b: DataFrame, mode: int) -> DataFrame:
    """Maximal runs of a mode's indices that more than one segment's interval covers: (lo, hi).

    Interval ends are swept with a running count over at most two rows a segment.
    """
    ends = b.select(F.col(f"lo{mode}").alias("at"), F.lit(1).alias("step")).union(b.select((F.col(f"hi{mode}") + 1).alias("at"), F.lit(-1).alias("step")))
    steps = ends.groupBy("at").agg(F.sum("step").alias("step"))
    line = Window.partitionBy(F.lit(0)).orderBy("at")  # two rows a segment at most
    swept = steps.select("at", F.sum("step").over(line).alias("depth"), F.lead("at").over(line).alias("next"))
    return swept.where("depth > 1").select(F.col("at").alias("lo"), (F.col("next") - 1).alias("hi"))


def with_boundary(rows: DataFrame, runs: DataFrame, length: int, segments: int) -> DataFrame:
    """rows (idx, …) with ``boundary``: whether a run of shared indices holds idx.

    Runs are cut at the borders of COVER_CELLS equal cells of the mode, so that rows find theirs by an equal key; there is
    at most one for each cell and two for each segment.
    """
    step = F.lit(-(-length // COVER_CELLS))
    cell = lambda c: F.floor(F.col(c) / step)
    cut = runs.select(F.struct("lo", "hi").alias("run"), F.explode(F.sequence(cell("lo"), cell("hi"))).alias("cell"))
    cells = cut.groupBy("cell").agg(F.collect_list("run").alias("runs"))
    met = rows.withColumn("cell", cell("idx")).join(F.broadcast(cells) if segments <= SMALL_BOXES else cells, "cell", "left")
    inside = F.exists("runs", lambda r: (r["lo"] <= F.col("idx")) & (F.col("idx") <= r["hi"]))
    return met.select(*rows.columns, F.coalesce(inside, F.lit(False)).alias("boundary"))


def flag_boundary(t: PackedTensor, mode: int, exclusive_by: str = "interval") -> PackedTensor:
    """df with ``boundary``: whether another segment may update the element's output row of this mode.

    ``interval`` asks the boxes, which is all that the format keeps; ``touch`` asks which segments
    really have elements in the row. Mode is 1-based.
    """
    rows = t.df.withColumn("idx", decode(t.plan, mode - 1))
    if exclusive_by == "touch":
        shared = rows.select("idx", "seg").distinct().groupBy("idx").agg((F.count(F.lit(1)) > 1).alias("boundary"))
        return t.with_df(rows.join(shared, "idx").drop("idx"))
    return t.with_df(with_boundary(rows, coverage(t.boxes, mode), t.shape.lengths[mode - 1], t.segments).drop("idx"))


def flag_in_spare_bit(t: PackedTensor) -> PackedTensor:
    """Move the boundary flag into the free bit above the position, where the first limb has one."""
    width = t.plan.bits - (t.plan.limbs - 1) * LIMB_BITS
    if width >= LIMB_BITS:
        return t  # no spare bit: the flag stays a column
    flag = F.when(F.col("boundary"), F.lit(1 << width)).otherwise(F.lit(0)).cast("long")
    return t.with_df(t.df.withColumn("p0", F.col("p0").bitwiseOR(flag)).drop("boundary"))


def flag_from_spare_bit(t: PackedTensor) -> PackedTensor:
    width = t.plan.bits - (t.plan.limbs - 1) * LIMB_BITS
    if width >= LIMB_BITS:
        return t
    df = t.df.withColumn("boundary", F.shiftright("p0", width) == 1)
    return t.with_df(df.withColumn("p0", F.col("p0").bitwiseAND(F.lit((1 << width) - 1).cast("long"))))


def merge(a: PackedTensor, b: PackedTensor) -> PackedTensor:
    """The sum of two tensors of one plan; cancelled elements are dropped."""
    if a.plan != b.plan:
        raise ValueError("tensors to merge need the same plan")
    by = a.positions
    df = a.df.select(*by, "val").unionByName(b.df.select(*by, "val"))
    return PackedTensor(df.groupBy(*by).agg(F.sum("val").alias("val")).where("val <> 0"), a.plan, a.shape)


def select_box(t: PackedTensor, box: dict[int, tuple[int, int]]) -> DataFrame:
    """Elements inside a box {mode (0-based): (lo, hi)}, as coordinates: points, fibers, slices or sub-boxes.

    The least and greatest position inside the box bound p0, which Parquet statistics can prune.
    """
    low, high = [0] * t.shape.order, [n - 1 for n in t.shape.lengths]
    for m, (a, b) in box.items():
        low[m], high[m] = max(low[m], a), min(high[m], b)
    shift = (t.plan.limbs - 1) * LIMB_BITS
    keep = F.lit(True)
    if all(a <= b for a, b in zip(low, high, strict=True)):
        bottom = sum(t.plan.encode_int([a if m == k else 0 for k in range(t.shape.order)]) & _floor_mask(t.plan, m, a, b) for m, (a, b) in enumerate(zip(low, high, strict=True)))
        top = sum(_ceiling(t.plan, m, a, b) for m, (a, b) in enumerate(zip(low, high, strict=True)))
        keep = F.col("p0").between(bottom >> shift, top >> shift)
    for m in box:
        keep = keep & decode(t.plan, m).between(low[m], high[m])
    return t.df.where(keep).select(*decode_all(t.plan), "val")


def _common(a: int, b: int) -> int:
    """Lowest level above which a and b agree."""
    return (a ^ b).bit_length()


def _floor_mask(plan: BitPlan, mode: int, a: int, b: int) -> int:
    """Position bits of the mode that all values from a to b share."""
    level = _common(a, b)
    return sum(1 << p for p, (m, at) in enumerate(plan.order) if m == mode and at >= level)


def _ceiling(plan: BitPlan, mode: int, a: int, b: int) -> int:
    """The mode's share of the greatest position: common bits of b, and ones below them."""
    level = _common(a, b)
    return sum((1 if at < level else (b >> at) & 1) << p for p, (m, at) in enumerate(plan.order) if m == mode)
