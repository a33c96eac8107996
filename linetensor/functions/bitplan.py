"""Bit plans: which bit of which mode sits at which bit of the position.

A plan turns the coordinates of a non-zero into one integer and back. The adaptive plan gives every
mode just the bits that its length needs and interleaves them from the low end, shortest mode
lowest, so short modes drop out early and the longest mode has the top bits. Positions wider than
63 bits take several BIGINT limbs ``p0, p1, …``, most significant first, so that signed comparison
orders them.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

LIMB_BITS = 63


def mode_bits(lengths: Sequence[int]) -> list[int]:
    """Whole bits that each mode needs: none for a length of one."""
    return [max(0, (n - 1).bit_length()) for n in lengths]


def ideal_bits(lengths: Sequence[int]) -> float:
    """Bits a position needs if fractions of bits could be used."""
    return sum(math.log2(n) for n in lengths)


@dataclass(frozen=True)
class BitPlan:
    """lengths of the modes, and for each position bit from the low end its (mode, level)."""

    lengths: tuple[int, ...]
    order: tuple[tuple[int, int], ...]
    kind: str = "adaptive"

    @classmethod
    def adaptive(cls, lengths: Sequence[int]) -> BitPlan:
        bits = mode_bits(lengths)
        by_length = sorted(range(len(lengths)), key=lambda m: (lengths[m], m))
        order = [(m, level) for level in range(max(bits, default=0)) for m in by_length if level < bits[m]]
        return cls(tuple(lengths), tuple(order))

    @classmethod
    def morton(cls, lengths: Sequence[int]) -> BitPlan:
        """The fractal curve: every mode has as many bits as the longest."""
        widest = max(mode_bits(lengths), default=0)
        return cls(tuple(lengths), tuple((m, level) for level in range(widest) for m in reversed(range(len(lengths)))), "morton")

    @classmethod
    def rowmajor(cls, lengths: Sequence[int]) -> BitPlan:
        """All bits of the last mode, then of the one before it, and so on."""
        bits = mode_bits(lengths)
        return cls(tuple(lengths), tuple((m, level) for m in reversed(range(len(lengths))) for level in range(bits[m])), "rowmajor")

    @property
    def bits(self) -> int:
        return len(self.order)

    @property
    def limbs(self) -> int:
        return max(1, -(-self.bits // LIMB_BITS))

    @property
    def columns(self) -> list[str]:
        """Names of the position's limbs, most significant first."""
        return [f"p{i}" for i in range(self.limbs)]

    def masks(self) -> list[int]:
        """For each mode the position bits it owns."""
        return [sum(1 << p for p, (m, _) in enumerate(self.order) if m == mode) for mode in range(len(self.lengths))]

    def groups(self) -> list[int]:
        """How many bits each level interleaves, from the low end."""
        levels = [level for _, level in self.order]
        return [levels.count(level) for level in range(max(levels, default=-1) + 1)]

    def line_length(self) -> int:
        return 1 << self.bits

    def subspace(self, top: int) -> list[int]:
        """Mode lengths of the sub-space that the top bits of a position single out (in powers of two)."""
        left = self.order[: self.bits - top]
        return [1 << sum(m == mode for m, _ in left) for mode in range(len(self.lengths))]

    def place(self, p: int) -> tuple[int, int]:
        """Limb column and bit of the limb where position bit p sits."""
        return self.limbs - 1 - p // LIMB_BITS, p % LIMB_BITS

    @cached_property
    def _by_mode(self) -> list[list[tuple[int, int]]]:
        found: list[list[tuple[int, int]]] = [[] for _ in self.lengths]
        for p, (m, level) in enumerate(self.order):
            found[m].append((level, p))
        return found

    def encode_int(self, coords: Sequence[int]) -> int:
        """One position in plain Python: for tests and small tables."""
        return sum(((coords[m] >> level) & 1) << p for p, (m, level) in enumerate(self.order))

    def decode_int(self, position: int) -> list[int]:
        out = [0] * len(self.lengths)
        for p, (m, level) in enumerate(self.order):
            out[m] |= ((position >> p) & 1) << level
        return out

    def sql(self, coords: Sequence[str]) -> str:
        """The position as a HUGEINT expression in DuckDB, bit by bit."""
        terms = [f"(({coords[m]} >> {level}) & 1)::HUGEINT * {1 << p}" for p, (m, level) in enumerate(self.order)]
        return " + ".join(terms) or "0::HUGEINT"

    def sql_limbs(self, position: str) -> list[str]:
        """The limbs of a HUGEINT position as BIGINT expressions in DuckDB."""
        size = 1 << LIMB_BITS
        if self.limbs == 1:
            return [f"({position})::BIGINT"]
        if self.limbs == 2:
            return [f"(({position}) // {size}::HUGEINT)::BIGINT", f"(({position}) % {size}::HUGEINT)::BIGINT"]
        raise ValueError("DuckDB integers hold two limbs")


def _table(values: Sequence[int]) -> Column:
    """A literal array of BIGINT; a constant to the optimizer."""
    return F.expr(f"array({','.join(f'{v}L' for v in values)})")


def _any(terms: list[Column]) -> Column:
    """Bitwise or as a balanced tree."""
    while len(terms) > 1:
        terms = [terms[i].bitwiseOR(terms[i + 1]) if i + 1 < len(terms) else terms[i] for i in range(0, len(terms), 2)]
    return terms[0] if terms else F.lit(0).cast("long")


def _byte(column: Column, k: int) -> Column:
    return F.shiftright(column, 8 * k).bitwiseAND(F.lit(255).cast("long")).cast("int")


def encode(plan: BitPlan, coords: Sequence[Column | str], impl: str = "tables") -> list[Column]:
    """The limbs of the position of these coordinates, named p0, p1, …

    ``tables`` looks up every byte of a coordinate in an array of 256 spread values, which keeps the
    generated code short; ``bits`` moves bit by bit.
    """
    columns = [F.col(c) if isinstance(c, str) else c for c in coords]
    out = []
    for limb, name in enumerate(plan.columns):
        terms = []
        for mode, column in enumerate(columns):
            column = column.cast("long")
            moves = [(level, bit) for level, p in plan._by_mode[mode] for at, bit in [plan.place(p)] if at == limb]
            if impl == "bits":
                terms += [F.shiftleft(F.shiftright(column, level).bitwiseAND(F.lit(1).cast("long")), bit) for level, bit in moves]
                continue
            for k in sorted({level // 8 for level, _ in moves}):
                inside = [(level - 8 * k, bit) for level, bit in moves if level // 8 == k]
                spread = [sum(((v >> level) & 1) << bit for level, bit in inside) for v in range(256)]
                terms.append(_table(spread)[_byte(column, k)])
        out.append(_any(terms).alias(name))
    return out


def decode(plan: BitPlan, mode: int, impl: str = "tables", prefix: str = "") -> Column:
    """Coordinate of one mode from the position's limbs."""
    terms = []
    for limb, name in enumerate(plan.columns):
        column = F.col(prefix + name)
        moves = [(level, bit) for level, p in plan._by_mode[mode] for at, bit in [plan.place(p)] if at == limb]
        if impl == "bits":
            terms += [F.shiftleft(F.shiftright(column, bit).bitwiseAND(F.lit(1).cast("long")), level) for level, bit in moves]
            continue
        for k in sorted({bit // 8 for _, bit in moves}):
            inside = [(level, bit - 8 * k) for level, bit in moves if bit // 8 == k]
            gathered = [sum(((v >> bit) & 1) << level for level, bit in inside) for v in range(256)]
            terms.append(_table(gathered)[_byte(column, k)])
    return _any(terms).alias(f"c{mode + 1}")


def decode_all(plan: BitPlan, impl: str = "tables") -> list[Column]:
    return [decode(plan, m, impl) for m in range(len(plan.lengths))]


def lin_to_binary(plan: BitPlan) -> Column:
    """The position as big-endian bytes, which sort as the position does."""
    return reduce(lambda a, b: F.concat(a, b), [F.unhex(F.lpad(F.hex(F.col(c)), 16, "0")) for c in plan.columns]).alias("line")
