"""Distinct combinations of coordinates, tiles and blocks, counted for many sets of them at once.

Grouping sets make a row of all columns for each element and set, and deal them all. Here sets that
have a column in common, or a finer one of the same mode, make a group. A task packs the distinct
combinations of what a group needs in bytes and deals them by that column, so that the sets of the
group are counted where equal combinations have met. A few groups have all sets of the storage model.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A mode (0-based) whose coordinates are divided by a number, rounded down.
Part = tuple[int, int]

#: Values that a column should have for elements to be dealt by it.
SPREAD = 1024
#: Elements packed at once, the logarithm of those counted at once, and the most buckets of a group.
PACK_ROWS, BUCKET_BITS, BUCKETS = 1 << 21, 17, 4096

DEALT = "deal int, bucket int, packed binary"
COUNTS = "of int, n long"


@dataclass(frozen=True)
class Deal:
    """A group: the part by which it is dealt, the parts that are sent, and the sets (their numbers and parts) counted of them."""

    by: Part
    sent: tuple[Part, ...]
    sets: tuple[tuple[int, tuple[Part, ...]], ...]


def plan_deals(sets: Sequence[tuple[Part, ...]], lengths: Sequence[int]) -> list[Deal]:
    """Groups that have every set once: again and again the column that deals most of the sets left, of those with enough values."""
    left, deals = dict(enumerate(sets)), []
    holds = lambda s, by: any(m == by[0] and by[1] % size == 0 for m, size in s)
    while left:
        values = lambda part: -(-lengths[part[0]] // part[1])
        by = max(sorted({p for s in left.values() for p in s}), key=lambda p: (min(values(p), SPREAD), sum(holds(s, p) for s in left.values()), values(p)))
        found = {k: s for k, s in left.items() if holds(s, by)}
        sizes: dict[int, int] = {}
        for m, size in (p for s in found.values() for p in s):
            sizes[m] = math.gcd(size, sizes.get(m, 0))
        sent = sorted(sizes.items(), key=lambda p: (p[0] != by[0], p))  # what it is dealt by comes first and changes least in their order
        deals.append(Deal(by, tuple(sent), tuple(found.items())))
        left = {k: s for k, s in left.items() if k not in found}
    return deals


def key_of(*columns: np.ndarray) -> np.ndarray:
    """One number for each combination, in the order of the columns."""
    key = np.zeros(len(columns[0]), np.int64)
    for c in columns:
        low = int(c.min())
        width = int(c.max()) - low + 1
        if (int(key.max()) + 1) * width >= 1 << 63:
            key, c, low = np.unique(key, return_inverse=True)[1], np.unique(c, return_inverse=True)[1], 0
            width = int(c.max()) + 1
        key = key * width + (c - low)
    return key


def count_distinct(*columns: np.ndarray) -> int:
    key = np.sort(key_of(*columns))
    return 1 + int(np.count_nonzero(key[1:] != key[:-1]))


def _bucket(values: np.ndarray, buckets: int) -> np.ndarray:
    mixed = values.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((mixed ^ mixed >> np.uint64(29)) >> np.uint64(32)).astype(np.int64) % buckets


def pack_runs(columns: Sequence[np.ndarray], starts: np.ndarray) -> Iterator[bytes]:
    """Each run of rows as its number of rows, every column's least value and width, and the bytes of their differences, place by place."""
    lows = [int(c.min()) for c in columns]
    widths = [((int(c.max()) - low).bit_length() + 7) // 8 for c, low in zip(columns, lows, strict=True)]
    places = np.hstack([(c - low).astype("<i8").view(np.uint8).reshape(-1, 8)[:, :width] for c, low, width in zip(columns, lows, widths, strict=True)])
    for a, b in zip(starts, np.append(starts[1:], len(places)), strict=True):
        yield np.array([b - a, *lows, *widths], "<i8").tobytes() + places[a:b].T.tobytes()


def unpack_run(data: bytes, columns: int) -> list[np.ndarray]:
    n, *rest = np.frombuffer(data, "<i8", 1 + 2 * columns).tolist()
    places = np.frombuffer(data, np.uint8, offset=8 * (1 + 2 * columns)).reshape(-1, n)
    out, at = [], 0
    for low, width in zip(rest[:columns], rest[columns:], strict=True):
        c = np.full(n, low, np.int64)
        for k in range(width):
            c += places[at + k].astype(np.int64) << 8 * k
        out.append(c)
        at += width
    return out


def pack_combinations(deals: Sequence[Deal], buckets: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """DEALT of rows with c1..cN."""
    held, rows = [], 0
    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows >= PACK_ROWS:
            yield from _packed(deals, buckets, held)
            held, rows = [], 0
    if rows:
        yield from _packed(deals, buckets, held)


def _packed(deals: Sequence[Deal], buckets: int, batches: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    table = pa.Table.from_batches(batches)
    modes = {m: table[f"c{m + 1}"].to_numpy() for m in sorted({m for d in deals for m, _ in d.sent})}
    for number, deal in enumerate(deals):
        columns = [modes[m] // size if size > 1 else modes[m] for m, size in deal.sent]
        bucket = _bucket(columns[0] // (deal.by[1] // deal.sent[0][1]), buckets)
        at = np.unique(key_of(bucket, *columns), return_index=True)[1]
        bucket = bucket[at]
        starts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
        packed = pa.array(list(pack_runs([c[at] for c in columns], starts)), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(starts), number, np.int32)), pa.array(bucket[starts].astype(np.int32)), packed], ["deal", "bucket", "packed"])


def count_combinations(deals: Sequence[Deal], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """COUNTS of DEALT in the order of groups and buckets: a row for each set."""
    found, held, at = Counter(), [], None
    for batch in batches:
        for deal, bucket, packed in zip(*(batch.column(c).to_pylist() for c in ("deal", "bucket", "packed")), strict=True):
            if held and (deal, bucket) != at:
                _count(deals[at[0]], held, found)
                held = []
            held.append(packed)
            at = deal, bucket
    if held:
        _count(deals[at[0]], held, found)
    yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int32()), pa.array(list(found.values()), pa.int64())], ["of", "n"])


def _count(deal: Deal, runs: list[bytes], found: Counter) -> None:
    columns = [np.concatenate(c) for c in zip(*(unpack_run(r, len(deal.sent)) for r in runs), strict=True)]
    sent = {m: (c, size) for (m, size), c in zip(deal.sent, columns, strict=True)}
    for number, parts in deal.sets:
        found[number] += count_distinct(*(sent[m][0] // (size // sent[m][1]) if size != sent[m][1] else sent[m][0] for m, size in parts))


def combination_counts(df: DataFrame, sets: Sequence[tuple[Part, ...]], lengths: Sequence[int]) -> list[int]:
    """How many distinct combinations each set has in the coordinates c1..cN of df. lengths: of the modes, to find columns that spread."""
    finer = lambda p, s: any(q != p and q[0] == p[0] and p[1] % q[1] == 0 for q in s)
    sets = [tuple(sorted({p for p in s if not finer(p, s)})) for s in sets]  # a coordinate has its tile and blocks
    each = sorted(set(sets))
    deals = plan_deals(each, lengths)
    buckets = min(BUCKETS, 1 << max(4, (df.count() >> BUCKET_BITS).bit_length()))
    rows = df.select(*[f"c{m + 1}" for m in sorted({m for s in each for m, _ in s})])
    dealt = rows.mapInArrow(partial(pack_combinations, deals, buckets), DEALT).repartition("deal", "bucket").sortWithinPartitions("deal", "bucket")
    counts = dealt.mapInArrow(partial(count_combinations, deals), COUNTS).groupBy("of").agg(F.sum("n").alias("n"))
    found = {each[r["of"]]: r["n"] for r in counts.collect()}  # a row for each set
    return [found.get(s, 0) for s in sets]
