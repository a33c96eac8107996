"""Matricized tensor times Khatri-Rao product, for one mode or all, from one packed copy.

Each element adds val times the product of the other modes' factor rows to the output row of its
own coordinate. ``buffered`` gathers partial rows inside every segment and merges them, ``direct``
sends every narrow element to the owner of its output row, ``flagged`` finishes rows that only one
segment can touch and merges the others; ``auto`` picks per mode by average reuse. Modes are 0-based.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bitplan import decode
from ..plans.choose import choose_delivery, choose_resolution, listable
from .factors import khatri_rao, rank_of, to_array, to_long
from .packed import PackedTensor, coverage, dealt, with_boundary

#: Components that one aggregate holds, to keep generated code in bounds.
RANK_CHUNK = 16


def _deliver(rows: DataFrame, factor: DataFrame, mode: int, length: int, delivery: str, nnz: int | None = None) -> DataFrame:
    """Join a mode's factor rows to the elements, whose coordinate is c{mode+1}."""
    rank = rank_of(factor)
    side = factor.select(F.col("idx").alias(f"c{mode + 1}"), *[F.col(f"f{r}").alias(f"f{mode}_{r}") for r in range(rank)])
    way = choose_delivery(length, rank, nnz) if delivery == "auto" else delivery
    if way == "broadcast":
        side = F.broadcast(side)
    elif way == "prefetch":  # only the rows that these elements ask for
        side = side.join(rows.select(f"c{mode + 1}").distinct(), f"c{mode + 1}", "left_semi")
    return rows.join(side, f"c{mode + 1}")


def _products(rows: DataFrame, factors: Sequence[DataFrame], mode: int, lengths: Sequence[int], delivery: str, keep: Sequence[str], nnz: int | None = None, form: str = "auto") -> DataFrame:
    """(keep…, y0..y{R-1}): the contribution of every element, by the form for this order. Shortest factors are joined first."""
    others = sorted((m for m in range(len(lengths)) if m != mode), key=lambda m: lengths[m])
    return kernel_dispatch(len(lengths), form)(rows, factors, others, lengths, delivery, keep, nnz)


def _products_at_once(rows: DataFrame, factors: Sequence[DataFrame], others: Sequence[int], lengths: Sequence[int], delivery: str, keep: Sequence[str], nnz: int | None) -> DataFrame:
    """For three and four modes: all factor rows side by side, and one projection that multiplies them."""
    for m in others:
        rows = _deliver(rows, factors[m], m, lengths[m], delivery, nnz)
    ys = [reduce(lambda a, m, r=r: a * F.col(f"f{m}_{r}"), others, F.col("val")).alias(f"y{r}") for r in range(rank_of(factors[others[0]]))]
    return rows.select(*keep, *ys)


def _products_by_mode(rows: DataFrame, factors: Sequence[DataFrame], others: Sequence[int], lengths: Sequence[int], delivery: str, keep: Sequence[str], nnz: int | None) -> DataFrame:
    """For any number of modes: one factor is multiplied in after another, so a row never has more than two sets of components."""
    rank = rank_of(factors[others[0]])
    ys = [F.col("val")] * rank
    for k, m in enumerate(others):
        rows = _deliver(rows, factors[m], m, lengths[m], delivery, nnz)
        products = [(y * F.col(f"f{m}_{r}")).alias(f"y{r}") for r, y in enumerate(ys)]
        rows = rows.select(*keep, *[f"c{x + 1}" for x in others[k + 1 :]], *products)
        ys = [F.col(f"y{r}") for r in range(rank)]
    return rows


#: Orders that have a form of their own.
SPECIALISED = {3: _products_at_once, 4: _products_at_once}


def kernel_dispatch(order: int, form: str = "auto"):
    """The form of the products for tensors of this order: a specialised one where there is any, unless the generic one is asked for."""
    return _products_by_mode if form == "generic" else SPECIALISED.get(order, _products_by_mode)


def _sums(rank: int) -> list[Column]:
    return [F.sum(f"y{r}").alias(f"y{r}") for r in range(rank)]


def _decoded(t: PackedTensor, mode: int, *extra: str) -> DataFrame:
    coords = [decode(t.plan, m) for m in range(t.shape.order) if m != mode]
    return t.df.select(*extra, decode(t.plan, mode).alias("idx"), *coords, "val")


def kr_sequential(t: PackedTensor, factors: Sequence[DataFrame], mode: int) -> DataFrame:
    """Everything in one task: the denominator of speedups, for tensors that one task can hold."""
    rows = _products(_decoded(t.with_df(t.df.coalesce(1)), mode), factors, mode, t.shape.lengths, "auto", ["idx"], t.nnz)
    return rows.coalesce(1).groupBy("idx").agg(*_sums(rank_of(factors[mode])))


def kr_buffered(t: PackedTensor, factors: Sequence[DataFrame], mode: int, delivery: str = "auto", form: str = "auto") -> DataFrame:
    """Partial rows inside each segment, then a merge of at most one row for each segment and index."""
    cut = dealt(t) if t.segments else t
    extra = ["seg"] if t.segments else []
    rows = _products(_decoded(cut, mode, *extra), factors, mode, t.shape.lengths, delivery, [*extra, "idx"], t.nnz, form)
    sums = _sums(rank_of(factors[mode]))
    if t.segments:
        rows = rows.groupBy("seg", "idx").agg(*sums)
    return rows.groupBy("idx").agg(*sums)


def kr_direct(t: PackedTensor, factors: Sequence[DataFrame], mode: int, delivery: str = "auto", form: str = "auto") -> DataFrame:
    """Narrow elements go to the owner of their output row before factors are joined."""
    narrow = t.df.select(decode(t.plan, mode).alias("idx"), *t.positions, "val").repartition("idx")
    coords = [decode(t.plan, m) for m in range(t.shape.order) if m != mode]
    rows = _products(narrow.select("idx", *coords, "val"), factors, mode, t.shape.lengths, delivery, ["idx"], t.nnz, form)
    return rows.groupBy("idx").agg(*_sums(rank_of(factors[mode])))


def kr_flagged(t: PackedTensor, factors: Sequence[DataFrame], mode: int, delivery: str = "auto", form: str = "auto") -> DataFrame:
    """Rows inside one segment's interval alone are finished there; the others are merged."""
    rank = rank_of(factors[mode])
    partial = _products(_decoded(dealt(t), mode, "seg"), factors, mode, t.shape.lengths, delivery, ["seg", "idx"], t.nnz, form).groupBy("seg", "idx").agg(*_sums(rank))
    flagged = with_boundary(partial, coverage(t.boxes, mode + 1), t.shape.lengths[mode], t.segments)
    internal = flagged.where(~F.col("boundary")).select("idx", *[f"y{r}" for r in range(rank)])
    return internal.unionByName(flagged.where("boundary").groupBy("idx").agg(*_sums(rank)))


def kr_array(t: PackedTensor, factors: Sequence[DataFrame], mode: int) -> DataFrame:
    """The rank as one array column: the generic form, any rank in the same plan."""
    rank = rank_of(factors[mode])
    rows = _decoded(t, mode)
    others = [m for m in range(t.shape.order) if m != mode]
    for m in others:
        side = to_array(factors[m]).select(F.col("idx").alias(f"c{m + 1}"), F.col("row").alias(f"row{m}"))
        rows = rows.join(F.broadcast(side) if listable(t.shape.lengths[m], rank) else side, f"c{m + 1}")
    product = F.transform(f"row{others[0]}", lambda x: x * F.col("val"))
    for m in others[1:]:
        product = F.zip_with(product, F.col(f"row{m}"), lambda a, b: a * b)
    rows = rows.select("idx", product.alias("y"))
    return rows.groupBy("idx").agg(*[F.sum(F.get("y", F.lit(r))).alias(f"y{r}") for r in range(rank)])


def kr_long(t: PackedTensor, factors: Sequence[DataFrame], mode: int) -> DataFrame:
    """The rank as a key: one row for each element and component, and only products that both factors have."""
    rank = rank_of(factors[mode])
    rows = _decoded(t, mode)
    for k, m in enumerate(m for m in range(t.shape.order) if m != mode):
        side = to_long(factors[m]).select(F.col("idx").alias(f"c{m + 1}"), "r", "v")
        side = F.broadcast(side) if listable(2 * t.shape.lengths[m], rank) else side  # an index and a component number for each value
        rows = rows.join(side, [f"c{m + 1}", "r"] if k else [f"c{m + 1}"]).withColumn("val", F.col("val") * F.col("v")).drop("v")
    summed = rows.groupBy("idx", "r").agg(F.sum("val").alias("v"))
    return summed.groupBy("idx").agg(*[F.sum(F.when(F.col("r") == r, F.col("v"))).alias(f"y{r}") for r in range(rank)])


def kr_arrow(t: PackedTensor, factors: Sequence[DataFrame], mode: int) -> DataFrame:
    """Vectorised partial rows in NumPy, for factors whose size is checked; merged by Spark."""
    rank, order = rank_of(factors[mode]), t.shape.order
    others = [m for m in range(order) if m != mode]
    if any(choose_delivery(t.shape.lengths[m], rank) != "broadcast" for m in others):
        raise ValueError("a factor is too large to travel with the tasks")
    held = {m: factors[m].orderBy("idx").toPandas().to_numpy()[:, 1:] for m in others}
    schema = "idx long, " + ", ".join(f"y{r} double" for r in range(rank))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = {n: c.to_numpy(zero_copy_only=False) for n, c in zip(batch.schema.names, batch.columns, strict=True)}
            product = columns["val"][:, None].astype(float)
            for m in others:
                product = product * held[m][columns[f"c{m + 1}"]]
            idx, at = np.unique(columns["idx"], return_inverse=True)
            out = np.zeros((len(idx), rank))
            np.add.at(out, at, product)
            yield pa.RecordBatch.from_arrays([pa.array(idx), *[pa.array(out[:, r]) for r in range(rank)]], names=["idx", *[f"y{r}" for r in range(rank)]])

    return _decoded(t, mode).mapInArrow(run, schema).groupBy("idx").agg(*_sums(rank))


def kr(t: PackedTensor, factors: Sequence[DataFrame], mode: int, resolve: str = "auto", rank_impl: str = "columns", delivery: str = "auto", form: str = "auto") -> DataFrame:
    """The kernel of one mode: (idx, y0..y{R-1}) for every index that has an element."""
    if rank_impl != "columns":
        return {"array": kr_array, "long": kr_long, "arrow": kr_arrow}[rank_impl](t, factors, mode)
    rank = rank_of(factors[mode])
    if rank > RANK_CHUNK:
        return _in_chunks(t, factors, mode, resolve, delivery, rank, form)
    if resolve == "auto":
        resolve = choose_resolution(t.count(), t.shape.lengths[mode])
        if resolve == "buffered":  # tasks hold ranges of the line already: each stages its own rows, and no element moves
            t = t.with_df(t.df, segments=None)
    if resolve == "sequential":
        return kr_sequential(t, factors, mode)
    return {"buffered": kr_buffered, "direct": kr_direct, "flagged": kr_flagged}[resolve](t, factors, mode, delivery, form)


def _in_chunks(t: PackedTensor, factors: Sequence[DataFrame], mode: int, resolve: str, delivery: str, rank: int, form: str) -> DataFrame:
    out = None
    for start in range(0, rank, RANK_CHUNK):
        some = range(start, min(rank, start + RANK_CHUNK))
        part = kr(t, [f.select("idx", *[F.col(f"f{r}").alias(f"f{r - start}") for r in some]) for f in factors], mode, resolve, "columns", delivery, form)
        part = part.select("idx", *[F.col(f"y{r - start}").alias(f"y{r}") for r in some])
        out = part if out is None else out.join(part, "idx")
    return out


def kr_all_modes(t: PackedTensor, factors: Sequence[DataFrame], resolve: str = "auto") -> list[DataFrame]:
    """One kernel for each mode over the same packed copy."""
    return [kr(t, factors, m, resolve) for m in range(t.shape.order)]


def densify(out: DataFrame, length: int) -> DataFrame:
    """A row for every index, zero where the tensor has no element."""
    ys = [c for c in out.columns if c != "idx"]
    every = out.sparkSession.range(length).withColumnRenamed("id", "idx")
    return every.join(out, "idx", "left").select("idx", *[F.coalesce(y, F.lit(0.0)).alias(y) for y in ys])


def unfold(df: DataFrame, mode: int, lengths: Sequence[int]) -> DataFrame:
    """The mode's unfolding of a coordinate list: row, column (mixed radix of the other modes) and val."""
    others = [m for m in range(len(lengths)) if m != mode]
    column = F.lit(0).cast("long")
    for m in others:
        column = column * lengths[m] + F.col(f"c{m + 1}")
    return df.select(F.col(f"c{mode + 1}").alias("row"), column.alias("col"), "val")


def kr_bruteforce(df: DataFrame, factors: Sequence[DataFrame], mode: int, lengths: Sequence[int]) -> DataFrame:
    """The definition: unfolding times the explicit Khatri-Rao product. For small shapes, as a reference."""
    others = [m for m in range(len(lengths)) if m != mode]
    product = factors[others[0]]
    for m in others[1:]:
        product = khatri_rao(product, factors[m])
    rank = rank_of(product)
    rows = unfold(df, mode, lengths).join(product.withColumnRenamed("idx", "col"), "col")
    return rows.groupBy(F.col("row").alias("idx")).agg(*[F.sum(F.col("val") * F.col(f"f{r}")).alias(f"y{r}") for r in range(rank)])
