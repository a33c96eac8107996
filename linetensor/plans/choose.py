"""Choices that the driver makes before a kernel runs."""

from __future__ import annotations

#: Memory operations that staging one output row costs at most: two reads and two writes.
BUFFER_COST_OPS = 4
#: Borders of the reuse classes.
HIGH_REUSE, MEDIUM_REUSE = 8, 5
#: Bytes of a factor that may be broadcast.
BROADCAST_BYTES = 256 << 20


def fiber_reuse(nnz: int, length: int) -> float:
    """Average number of non-zeros that update one output row of a mode."""
    return nnz / length


def classify_reuse(reuse: float, rounding: str | None = None) -> str:
    """high above 8, medium from 5 to 8, else limited; 'nearest' rounds to a whole number first."""
    value = round(reuse) if rounding == "nearest" else reuse
    return "high" if value > HIGH_REUSE else "medium" if value >= MEDIUM_REUSE else "limited"


def tensor_class(nnz: int, lengths, rounding: str | None = None) -> str:
    """The class of the mode with the least reuse."""
    return classify_reuse(min(fiber_reuse(nnz, n) for n in lengths), rounding)


def choose_resolution(nnz: int, length: int, cost: float = BUFFER_COST_OPS) -> str:
    """buffered if a row's updates outnumber the operations that staging it costs, else direct."""
    return "buffered" if fiber_reuse(nnz, length) > cost else "direct"


def choose_by_bytes(nnz: int, partial_rows: int, rank: int, limbs: int) -> str:
    """The same choice by shuffled bytes: partial rows of rank doubles against narrow elements."""
    return "buffered" if partial_rows * (8 + 8 * rank) < nnz * (8 * limbs + 16) else "direct"


def choose_delivery(length: int, rank: int, nnz: int | None = None, limit: int = BROADCAST_BYTES) -> str:
    """broadcast a factor whose size is below the limit; beyond, prefetch the rows that occur where they are fewer than the mode is long, else shuffle."""
    if length * (8 + 8 * rank) <= limit:
        return "broadcast"
    return "prefetch" if nnz is not None and nnz < length else "shuffle"


def listable(length: int, rank: int) -> bool:
    """Whether a mode is short enough that a factor may have a row for every index; a longer one has rows for those that occur."""
    return choose_delivery(length, rank) == "broadcast"
