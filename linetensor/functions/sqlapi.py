"""SQL surface: functions of a packed tensor's plan, and table functions that show plans."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .bitplan import BitPlan


def _table_sql(values: list[int], byte: str) -> str:
    return f"element_at(array({','.join(f'{v}L' for v in values)}), CAST({byte} AS INT) + 1)"


def _spread_sql(plan: BitPlan, mode: int, limb: int, column: str) -> list[str]:
    moves = [(level, bit) for level, p in plan._by_mode[mode] for at, bit in [plan.place(p)] if at == limb]
    out = []
    for k in sorted({level // 8 for level, _ in moves}):
        inside = [(level - 8 * k, bit) for level, bit in moves if level // 8 == k]
        out.append(_table_sql([sum(((v >> level) & 1) << bit for level, bit in inside) for v in range(256)], f"(shiftright({column}, {8 * k}) & 255L)"))
    return out


def register(spark: SparkSession, plan: BitPlan, suffix: str) -> None:
    """lin_encode_<suffix>(c1, …), one function for each limb, and lin_decode_<suffix>_<mode>(p0, …).

    They are SQL functions, which the analyzer inlines, so plans hold plain expressions.
    """
    args = ", ".join(f"c{m + 1} BIGINT" for m in range(len(plan.lengths)))
    for limb, name in enumerate(plan.columns):
        terms = [x for m in range(len(plan.lengths)) for x in _spread_sql(plan, m, limb, f"c{m + 1}")]
        end = f"_{name}" if plan.limbs > 1 else ""
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lin_encode_{suffix}{end}({args}) RETURNS BIGINT RETURN {' | '.join(terms) or '0L'}")
    limbs = ", ".join(f"{p} BIGINT" for p in plan.columns)
    for mode in range(len(plan.lengths)):
        terms = []
        for limb, name in enumerate(plan.columns):
            moves = [(level, bit) for level, p in plan._by_mode[mode] for at, bit in [plan.place(p)] if at == limb]
            for k in sorted({bit // 8 for _, bit in moves}):
                inside = [(level, bit - 8 * k) for level, bit in moves if bit // 8 == k]
                terms.append(_table_sql([sum(((v >> bit) & 1) << level for level, bit in inside) for v in range(256)], f"(shiftright({name}, {8 * k}) & 255L)"))
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lin_decode_{suffix}_{mode + 1}({limbs}) RETURNS BIGINT RETURN {' | '.join(terms) or '0L'}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fiber_reuse(nnz BIGINT, length BIGINT) RETURNS DOUBLE RETURN nnz / length")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tensor_density(nnz BIGINT, cells DOUBLE) RETURNS DOUBLE RETURN nnz / cells")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION metadata_ratio(coo_bits BIGINT, packed_bits BIGINT) RETURNS DOUBLE RETURN coo_bits / packed_bits")


@udtf(returnType="position: int, mode: int, level: int")
class ShowPlan:
    """One row for each position bit of the adaptive plan of these lengths."""

    def eval(self, lengths: list) -> Iterator[tuple[int, int, int]]:
        for p, (m, level) in enumerate(BitPlan.adaptive(lengths).order):
            yield p, m + 1, level


@udtf(returnType="position: int, mode: int, level: int")
class ShowMortonPlan:
    """The same for the fractal curve."""

    def eval(self, lengths: list) -> Iterator[tuple[int, int, int]]:
        for p, (m, level) in enumerate(BitPlan.morton(lengths).order):
            yield p, m + 1, level


def register_table_functions(spark: SparkSession) -> None:
    spark.udtf.register("bit_plan", ShowPlan)
    spark.udtf.register("morton_plan", ShowMortonPlan)
