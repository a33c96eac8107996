"""Named queries over the given tables, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import measures
from .functions.bitplan import LIMB_BITS, BitPlan, decode, decode_all
from .operators import algebra, baselines
from .operators.factors import RANK, factor_sql, gram, init_factor, init_factors
from .operators.kernels import densify, kr, kr_all_modes, kr_bruteforce, unfold
from .operators.packed import (
    PackedTensor,
    box_overlaps,
    coverage,
    flag_boundary,
    flag_from_spare_bit,
    flag_in_spare_bit,
    infer_shape,
    merge,
    pack,
    prefix_partition,
    segment,
    select_box,
    unpack,
)
from .operators.wordlists import word_counts
from .plans.choose import choose_resolution, classify_reuse, fiber_reuse, listable, tensor_class
from .plans.cpals import cp_als, packed_kernel
from .sources.tables import read_table
from .sources.tensors import checkpointed, passing
from .sources.workloads import SMALL, WORKLOADS, Workload, w6_texts

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
SEGMENTS = 8
#: Indices of a tile of the tiled trees.
TILE = 64
MORTON_MOST = 126


def register(name: str, function: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = function
    if sql:
        ORACLES[name] = sql


def packed(spark: SparkSession, d: str, w: Workload, kind: str = "adaptive") -> PackedTensor:
    df = w.build(spark, d)
    if kind == "adaptive":
        return pack(df, names=w.modes)
    shape = infer_shape(df, w.modes)
    return pack(df, shape, getattr(BitPlan, kind)(shape.lengths))


def factors_for(t: PackedTensor, w: Workload, rank: int = RANK) -> list[DataFrame]:
    """Factors with a row for every index of a mode, or for those that occur where a mode is too long to be listed."""
    spark = t.df.sparkSession
    occurring = lambda m: None if listable(t.shape.lengths[m], rank) else t.df.select(decode(t.plan, m).alias("idx")).distinct()
    return [init_factor(spark, n, rank, m, w.denominator, occurring(m)) for m, n in enumerate(t.shape.lengths)]


# --- SQL building blocks. Lengths are known to SQL only as max + 1, so a position is built from
# ranks of modes by (length, number) and levels, which is what an adaptive plan does.


def _coo_cte(w: Workload) -> str:
    return f"coo AS ({w.sql})"


def _lengths_cte(w: Workload) -> str:
    union = " UNION ALL ".join(f"SELECT {m} AS mode, max(c{m + 1}) + 1 AS length FROM coo" for m in range(w.order))
    return f"lengths AS ({union}), bits AS (SELECT mode, length, CASE WHEN length <= 1 THEN 0 ELSE ceil(log2(length))::BIGINT END AS bits FROM lengths)"


def _plan_cte(kind: str) -> str:
    """Position bits with the mode and level that they hold."""
    order = {"adaptive": "level, length, mode", "morton": "level, mode DESC", "rowmajor": "mode DESC, level"}[kind]
    most = "(SELECT max(bits) FROM bits)" if kind == "morton" else "bits"
    return f"plan AS (SELECT mode, level, row_number() OVER (ORDER BY {order}) - 1 AS p FROM (SELECT mode, length, unnest(range({most})) AS level FROM bits))"


def _weights_cte(w: Workload) -> str:
    """One row with, for every mode, the list of position weights of its levels."""
    each = ", ".join(f"coalesce(list(pow2 ORDER BY level) FILTER (mode = {m}), []) AS w{m}" for m in range(w.order))
    return f"powers AS (SELECT mode, level, CASE WHEN p < 62 THEN (1::HUGEINT << p::INT) ELSE (1::HUGEINT << 62) * (1::HUGEINT << (p - 62)::INT) END AS pow2 FROM plan), weights AS (SELECT {each} FROM powers)"


def _position(w: Workload) -> str:
    parts = [f"coalesce(list_sum(list_transform(w{m}, lambda x, i: ((c{m + 1} >> (i - 1)::INT) & 1)::HUGEINT * x)), 0)" for m in range(w.order)]
    return "(" + " + ".join(parts) + ")::HUGEINT"


def _encoded(w: Workload, kind: str = "adaptive") -> str:
    """CTEs up to ``line``: coordinates, val and the position pos."""
    return f"WITH {_coo_cte(w)}, {_lengths_cte(w)}, {_plan_cte(kind)}, {_weights_cte(w)}, line AS (SELECT coo.*, {_position(w)} AS pos FROM coo, weights)"


def _limbs_sql(limbs: int) -> str:
    size = 1 << LIMB_BITS
    return "pos::BIGINT AS p0" if limbs == 1 else f"(pos // {size}::HUGEINT)::BIGINT AS p0, (pos % {size}::HUGEINT)::BIGINT AS p1"


def _kernel_sql(w: Workload, mode: int, rank: int = RANK, source: str | None = None) -> str:
    ys = []
    for r in range(rank):
        product = " * ".join(["val", *[factor_sql(m, f"c{m + 1}", r, w.denominator) for m in range(w.order) if m != mode]])
        ys.append(f"sum({product}) AS y{r}")
    return f"SELECT c{mode + 1} AS idx, {', '.join(ys)} FROM ({source or w.sql}) GROUP BY c{mode + 1}"


def _limbs(w: Workload) -> int:
    return 2 if w.name == "w07" else 1


# --- tensors


def _profile(spark: SparkSession, d: str, w: Workload) -> DataFrame:
    t = packed(spark, d, w)
    rows = [(w.name, m + 1, name, n, measures.fiber_reuse(t.count(), n), classify_reuse(fiber_reuse(t.count(), n)), tensor_class(t.count(), t.shape.lengths), choose_resolution(t.count(), n)) for m, (name, n) in enumerate(zip(t.shape.names, t.shape.lengths, strict=True))]
    return spark.createDataFrame(rows, "workload string, mode long, name string, length long, reuse double, reuse_class string, tensor_class string, resolution string")


def _class_sql(x: str) -> str:
    return f"CASE WHEN {x} > 8 THEN 'high' WHEN {x} >= 5 THEN 'medium' ELSE 'limited' END"


for _w in WORKLOADS.values():
    register(f"{_w.name}_coo", lambda s, d, w=_w: w.build(s, d), _w.sql)
    _names = "CASE mode " + " ".join(f"WHEN {m} THEN '{n}'" for m, n in enumerate(_w.modes)) + " END"
    register(
        f"{_w.name}_profile",
        lambda s, d, w=_w: _profile(s, d, w),
        f"WITH {_coo_cte(_w)}, {_lengths_cte(_w)}, n AS (SELECT count(*) AS nnz FROM coo), r AS (SELECT mode, length, nnz / length::DOUBLE AS reuse FROM lengths, n) "
        f"SELECT '{_w.name}' AS workload, (mode + 1)::BIGINT AS mode, {_names} AS name, length::BIGINT AS length, reuse, {_class_sql('reuse')} AS reuse_class, {_class_sql('(SELECT min(reuse) FROM r)')} AS tensor_class, CASE WHEN reuse > 4 THEN 'buffered' ELSE 'direct' END AS resolution FROM r",
    )
    register(f"{_w.name}_encode", lambda s, d, w=_w: packed(s, d, w).df, f"{_encoded(_w)} SELECT {_limbs_sql(_limbs(_w))}, val FROM line")
    register(f"{_w.name}_roundtrip", lambda s, d, w=_w: unpack(packed(s, d, w)), _w.sql)

for _n in ("w01", "w04", "w05", "w12"):
    for _kind in ("morton", "rowmajor"):
        register(f"{_n}_encode_{_kind}", lambda s, d, w=WORKLOADS[_n], k=_kind: packed(s, d, w, k).df, f"{_encoded(WORKLOADS[_n], _kind)} SELECT {_limbs_sql(1)}, val FROM line")

register(
    "w01_encode_bits",
    lambda s, d: pack(WORKLOADS["w01"].build(s, d), impl="bits").df,
    f"{_encoded(WORKLOADS['w01'])} SELECT {_limbs_sql(1)}, val FROM line",
)


def _line_order(spark: SparkSession, d: str) -> DataFrame:
    """Elements that stand before their neighbour on the line: none, within each stored partition."""
    from pyspark.sql import Window

    from .operators.packed import sort_line

    df = sort_line(packed(spark, d, WORKLOADS["w01"])).df.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id())
    before = F.lag("p0").over(Window.partitionBy("part").orderBy("at"))
    return df.select("p0", before.alias("before")).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("before") >= F.col("p0")).cast("long")).alias("out_of_order"))


register("w01_sorted", _line_order, f"SELECT count(*)::BIGINT AS n, 0::BIGINT AS out_of_order FROM ({WORKLOADS['w01'].sql})")

# --- segments, boxes, balance, conflicts


def cut(spark: SparkSession, d: str, w: Workload) -> PackedTensor:
    return segment(packed(spark, d, w), SEGMENTS)


def _segmented(w: Workload) -> str:
    return f"{_encoded(w)}, cut AS (SELECT *, row_number() OVER (ORDER BY pos) - 1 AS rnk, ntile({SEGMENTS}) OVER (ORDER BY pos) - 1 AS seg FROM line)"


def _boxes_sql(w: Workload) -> str:
    spans = ", ".join(f"min(c{m + 1})::BIGINT AS lo{m + 1}, max(c{m + 1})::BIGINT AS hi{m + 1}" for m in range(w.order))
    size = 1 << LIMB_BITS
    if _limbs(w) == 1:
        ends = "min(pos)::BIGINT AS p0_min, max(pos)::BIGINT AS p0_max"
    else:
        ends = ", ".join(f"({f}(pos) {op} {size}::HUGEINT)::BIGINT AS p{i}_{f}" for f in ("min", "max") for i, op in enumerate(("//", "%")))
    return f"boxes AS (SELECT seg, count(*) AS n, {ends}, {spans} FROM cut GROUP BY seg)"


def _flag_sql(w: Workload, mode: int, by: str) -> str:
    if by == "touch":
        rows = f"hit AS (SELECT c{mode} AS ix, count(DISTINCT seg) > 1 AS boundary FROM cut GROUP BY 1)"
    else:
        rows = f"rows AS (SELECT DISTINCT c{mode} AS ix FROM cut), hit AS (SELECT ix, (SELECT count(*) FROM boxes WHERE ix BETWEEN lo{mode} AND hi{mode}) > 1 AS boundary FROM rows)"
    return f"{_segmented(w)}, {_boxes_sql(w)}, {rows} SELECT seg, sum(boundary::INT)::BIGINT AS boundary, count(*) AS n FROM cut JOIN hit ON c{mode} = ix GROUP BY seg"


def _flags(spark: SparkSession, d: str, w: Workload, mode: int, by: str) -> DataFrame:
    t = flag_boundary(cut(spark, d, w), mode, by)
    if by == "interval":  # the flag travels in the spare bit and is read back
        t = flag_from_spare_bit(flag_in_spare_bit(t))
    return t.df.groupBy("seg").agg(F.sum(F.col("boundary").cast("long")).alias("boundary"), F.count(F.lit(1)).alias("n"))


def _overlap_sql(w: Workload) -> str:
    modes = range(1, w.order + 1)
    meet = " AND ".join(f"x.lo{m} <= y.hi{m} AND y.lo{m} <= x.hi{m}" for m in modes)
    shared = ", ".join(f"least(x.hi{m}, y.hi{m}) - greatest(x.lo{m}, y.lo{m}) + 1 AS shared{m}" for m in modes)
    return f"{_segmented(w)}, {_boxes_sql(w)} SELECT x.seg AS seg_a, y.seg AS seg_b, {shared} FROM boxes x JOIN boxes y ON x.seg < y.seg AND {meet}"


def _prefix_sql(w: Workload, bits: int) -> str:
    return f"{_encoded(w)} SELECT (pos // pow(2, greatest(0, (SELECT sum(bits) FROM bits) - {bits}))::HUGEINT)::BIGINT AS prefix, count(*) AS n FROM line GROUP BY 1"


for _n in ("w01", "w02", "w05", "w07", "w08"):
    _w = WORKLOADS[_n]
    register(f"segments_{_n}", lambda s, d, w=_w: cut(s, d, w).df.select("seg", "rnk", *(f"p{i}" for i in range(_limbs(w)))), f"{_segmented(_w)} SELECT seg, rnk, {_limbs_sql(_limbs(_w))} FROM cut")
    register(f"boxes_{_n}", lambda s, d, w=_w: cut(s, d, w).boxes, f"{_segmented(_w)}, {_boxes_sql(_w)} SELECT * FROM boxes")
    register(f"overlaps_{_n}", lambda s, d, w=_w: box_overlaps(cut(s, d, w).boxes, w.order), _overlap_sql(_w))
    for _m in (1, _w.order):
        _touched = f"t AS (SELECT c{_m} AS ix, count(DISTINCT seg) AS segs, count(*) AS n FROM cut GROUP BY 1)"
        register(
            f"conflicts_{_n}_m{_m}",
            lambda s, d, w=_w, m=_m: measures.conflict_stats(cut(s, d, w), m - 1),
            f"{_segmented(_w)}, {_touched} SELECT count(*) AS rows_touched, sum((segs > 1)::INT)::BIGINT AS rows_shared, sum(segs)::BIGINT AS partial_rows, coalesce(sum(n) FILTER (segs > 1), 0)::BIGINT AS elements_shared FROM t",
        )
        register(
            f"staging_{_n}_m{_m}",
            lambda s, d, w=_w, m=_m: measures.staging_bytes(cut(s, d, w).boxes, m, RANK),
            f"{_segmented(_w)}, {_boxes_sql(_w)} SELECT sum(hi{_m} - lo{_m} + 1)::BIGINT AS width, (sum(hi{_m} - lo{_m} + 1) * {8 * RANK})::BIGINT AS bytes FROM boxes",
        )

for _n, _m in (("w01", 1), ("w01", 2), ("w02", 1), ("w05", 1), ("w07", 1)):
    for _by in ("interval", "touch"):
        register(f"flags_{_n}_m{_m}_{_by}", lambda s, d, w=WORKLOADS[_n], m=_m, b=_by: _flags(s, d, w, m, b), _flag_sql(WORKLOADS[_n], _m, _by))

for _n in ("w01", "w05", "w06"):
    register(f"prefix_partition_{_n}", lambda s, d, w=WORKLOADS[_n]: prefix_partition(packed(s, d, w), 5), _prefix_sql(WORKLOADS[_n], 5))


def _imbalance(spark: SparkSession, d: str, w: Workload) -> DataFrame:
    """Greatest over mean count of segments, prefixes, blocks, slices and fibers."""
    t = cut(spark, d, w)
    coo = unpack(t)
    keys = [f"c{m + 1}" for m in range(w.order)]
    blocks = coo.select(*[F.shiftright(k, 7).alias(k) for k in keys])
    first = t.df.withColumn("prefix", F.shiftright("p0", max(0, t.plan.bits - (t.plan.limbs - 1) * LIMB_BITS - 3)))
    parts = {"segment": measures.imbalance(t.df, "seg"), "prefix": measures.imbalance(first, "prefix"), "block": measures.imbalance(blocks, *keys), "slice": measures.imbalance(coo, keys[0]), "fiber": measures.imbalance(coo, *keys[1:])}
    named = [df.select(F.lit(k).alias("partitioning"), F.col("parts").cast("long").alias("parts"), F.col("most").cast("long").alias("most"), "mean", "imbalance") for k, df in parts.items()]
    return reduce(DataFrame.unionByName, named)


def _imbalance_sql(w: Workload) -> str:
    keys = [f"c{m + 1}" for m in range(w.order)]
    by = {"segment": "seg", "prefix": "(pos // pow(2, greatest(0, (SELECT sum(bits) FROM bits) - 3))::HUGEINT)", "block": ", ".join(f"{k} >> 7" for k in keys), "slice": keys[0], "fiber": ", ".join(keys[1:])}
    parts = [f"SELECT '{name}' AS partitioning, count(*) AS parts, max(n)::BIGINT AS most, avg(n) AS mean, max(n) / avg(n) AS imbalance FROM (SELECT count(*) AS n FROM cut GROUP BY {keys_})" for name, keys_ in by.items()]
    return f"{_segmented(w)} " + " UNION ALL ".join(parts)


for _n in ("w01", "w05", "w06"):
    register(f"imbalance_{_n}", lambda s, d, w=WORKLOADS[_n]: _imbalance(s, d, w), _imbalance_sql(WORKLOADS[_n]))

for _w in WORKLOADS.values():
    _blocks = ", ".join(f"c{m + 1} >> 7" for m in range(_w.order))
    register(
        f"block_stats_{_w.name}",
        lambda s, d, w=_w: measures.block_stats(w.build(s, d)),
        f"SELECT count(*) AS blocks, min(n)::BIGINT AS least, quantile_cont(n, 0.25)::DOUBLE AS q1, quantile_cont(n, 0.5)::DOUBLE AS median, quantile_cont(n, 0.75)::DOUBLE AS q3, max(n)::BIGINT AS most, avg(n) AS mean FROM (SELECT count(*) AS n FROM ({_w.sql}) GROUP BY {_blocks})",
    )

# --- storage


def _storage(spark: SparkSession, d: str, w: Workload) -> DataFrame:
    """Bytes of every format, with values, and relative to the coordinate list; levels of trees have the declared order."""
    by = ORDER_OF_LENGTHS[w.name]
    if w.name == "w06":  # nearly as many elements as words of all texts: counted from lists of places
        counts, lengths = word_counts(w6_texts(spark, d), TILE)
        within = lambda s: tuple(sorted(k for k in s if k[0] != "t" or f"c{k[1:]}" not in s))
        found = measures.storage_model(lambda sets: {tuple(sorted(s)): counts.get(within(s), 0) for s in sets}, lengths, by)
    else:
        with passing(spark) as keep:
            coo = keep(w.build(spark, d).drop("val"))
            found = measures.storage_bytes(coo, infer_shape(coo, w.modes).lengths, TILE, by)
    return spark.createDataFrame([(w.name, f, b, found["coo"] / b) for f, b in found.items()], "workload string, format string, bytes long, ratio double")


def _storage_sql(w: Workload, shape: tuple[int, ...]) -> str:
    """Storage by the model; tree levels follow the order of these lengths."""
    keys = [f"c{m + 1}" for m in range(w.order)]
    n = w.order
    parts = [
        f"SELECT 'coo' AS format, nnz * {8 * n + 8} AS bytes FROM n",
        "SELECT 'packed', nnz * (8 * greatest(1, ceil((SELECT sum(bits) FROM bits) / 64.0))::BIGINT + 8) FROM n",
    ]
    for bits in (10, 14):
        b, s = ", ".join(f"{k} >> 7" for k in keys), ", ".join(f"{k} >> {bits}" for k in keys)
        parts.append(f"SELECT 'blk{bits}', nnz * {n + 8} + (SELECT count(*) FROM (SELECT DISTINCT {b} FROM coo)) * {4 * n + 8} + (SELECT count(*) FROM (SELECT DISTINCT {s} FROM coo)) * 8 FROM n")
    for name in ("csf", "csf_tile"):
        trees = []
        for root in range(n):
            path = [f"c{m + 1}" for m in baselines.tree_levels(shape, root)]
            path = [f"{path[-1]} // {TILE}", *path] if name == "csf_tile" else path
            counts = [f"(SELECT count(*) FROM (SELECT DISTINCT {', '.join(path[: k + 1])} FROM coo))" for k in range(len(path))]
            trees.append(" + ".join([f"8 * {c}" for c in counts] + [f"8 * ({c} + 1)" for c in counts[:-1]] + ["8 * nnz"]))
        parts.append(f"SELECT '{name}', {' + '.join(trees)} FROM n")
    union = " UNION ALL ".join(parts)
    return f"WITH {_coo_cte(w)}, {_lengths_cte(w)}, n AS (SELECT count(*) AS nnz FROM coo), s AS ({union}) SELECT '{w.name}' AS workload, format, bytes::BIGINT AS bytes, (SELECT bytes FROM s WHERE format = 'coo') / bytes::DOUBLE AS ratio FROM s"


#: Declared mode lengths of the workloads; only their order matters, for the levels of trees in SQL and in Spark at every scale.
ORDER_OF_LENGTHS = {
    "w01": (2000, 100, 83),
    "w02": (15000, 2000, 7),
    "w03": (2000, 100, 83),
    "w04": (1500, 79, 5),
    "w05": (150, 5, 30, 24),
    "w06": (1000, 93796, 20),
    "w07": (10000, 150, 5, 2591832194063, 100),
    "w08": (1500, 2000, 100, 2500, 3),
    "w09": (25, 25, 6, 7),
    "w10": (150, 5, 30, 24, 100),
    "w11": (500, 64),
    "w12": (100, 8, 3),
}
for _n, _shape in ORDER_OF_LENGTHS.items():
    register(f"storage_{_n}", lambda s, d, w=WORKLOADS[_n]: _storage(s, d, w), _storage_sql(WORKLOADS[_n], _shape))

#: Families of formats that are compared: one copy for any mode, or a copy for each.
FAMILIES = {"general": ("coo", "blk10", "blk14"), "specific": ("csf", "csf_tile")}


def _compression(spark: SparkSession, d: str) -> DataFrame:
    """For each tensor and family the bytes of its best format over ours, and the geometric means."""
    rows = []
    for w in WORKLOADS.values():
        found = {r["format"]: r["bytes"] for r in _storage(spark, d, w).collect()}
        rows += [(w.name, family, min(found[f] for f in formats) / found["packed"]) for family, formats in FAMILIES.items()]
    df = spark.createDataFrame(rows, "workload string, family string, compression double")
    means = df.groupBy("family").agg(measures.geomean("compression").alias("compression")).select(F.lit("geomean").alias("workload"), "family", "compression")
    return df.unionByName(means).withColumn("compression", F.round("compression", 9))


def _compression_sql() -> str:
    every = " UNION ALL ".join(f"SELECT workload, format, bytes FROM ({_storage_sql(WORKLOADS[n], shape)})" for n, shape in ORDER_OF_LENGTHS.items())
    of = " ".join(f"WHEN s.format IN {formats} THEN '{family}'" for family, formats in FAMILIES.items())
    best = f"SELECT s.workload, CASE {of} END AS family, min(s.bytes) / any_value(p.bytes)::DOUBLE AS compression FROM s JOIN (SELECT * FROM s WHERE format = 'packed') p USING (workload) WHERE s.format <> 'packed' GROUP BY 1, 2"
    return f"WITH s AS ({every}), best AS ({best}) SELECT workload, family, round(compression, 9) AS compression FROM best UNION ALL SELECT 'geomean', family, round(exp(avg(ln(compression))), 9) FROM best GROUP BY family"


register("compression_summary", _compression, _compression_sql())


def _ratios(spark: SparkSession, d: str) -> DataFrame:
    """Formula measures of all workloads, and their geometric means."""
    rows = []
    for w in WORKLOADS.values():
        t = packed(spark, d, w)
        rows += [(w.name, k, float(v)) for k, v in measures.profile(t.shape.lengths, t.count()).items()]
    df = spark.createDataFrame(rows, "workload string, metric string, value double")
    means = df.groupBy("metric").agg(measures.geomean("value").alias("value")).select(F.lit("geomean").alias("workload"), "metric", "value")
    return df.unionByName(means)


register("measures_all", _ratios)

# --- kernels


def kernel_query(n: str, mode: int, resolve: str, **options) -> Callable[[SparkSession, str], DataFrame]:
    w = WORKLOADS[n]

    def run(spark: SparkSession, d: str) -> DataFrame:
        t = packed(spark, d, w)
        if resolve in ("buffered", "flagged"):
            t = segment(t, SEGMENTS)
        return kr(t, factors_for(t, w), mode - 1, resolve, **options)

    return run


for _n in WORKLOADS:
    for _m in range(1, WORKLOADS[_n].order + 1):
        register(f"kr_{_n}_m{_m}_auto", kernel_query(_n, _m, "auto"), _kernel_sql(WORKLOADS[_n], _m - 1))
for _n in ("w01", "w02", "w03", "w04", "w07"):
    for _r in ("buffered", "direct", "flagged"):
        register(f"kr_{_n}_m1_{_r}", kernel_query(_n, 1, _r), _kernel_sql(WORKLOADS[_n], 0))
for _n in ("w01", "w04", "w05"):
    register(f"kr_{_n}_m1_order_generic", kernel_query(_n, 1, "direct", form="generic"), _kernel_sql(WORKLOADS[_n], 0))
register("kr_w01_m1_sequential", kernel_query("w01", 1, "sequential"), _kernel_sql(WORKLOADS["w01"], 0))
for _i in ("array", "long", "arrow"):
    register(f"kr_w01_m1_rank_{_i}", kernel_query("w01", 1, "auto", rank_impl=_i), _kernel_sql(WORKLOADS["w01"], 0))
for _v in ("broadcast", "shuffle", "prefetch"):
    register(f"kr_w01_m1_factors_{_v}", kernel_query("w01", 1, "direct", delivery=_v), _kernel_sql(WORKLOADS["w01"], 0))


def _dense(spark: SparkSession, d: str) -> DataFrame:
    w = WORKLOADS["w04"]
    t = packed(spark, d, w)
    return densify(kr(t, factors_for(t, w), 0, "direct"), t.shape.lengths[0])


_zero = ", ".join(f"coalesce(y{r}, 0) AS y{r}" for r in range(RANK))
register("kr_w04_m1_dense", _dense, f"WITH k AS ({_kernel_sql(WORKLOADS['w04'], 0)}) SELECT i.idx, {_zero} FROM (SELECT unnest(range((SELECT max(idx) + 1 FROM k))) AS idx) i LEFT JOIN k USING (idx)")


def _all_modes(spark: SparkSession, d: str, n: str) -> DataFrame:
    w = WORKLOADS[n]
    t = packed(spark, d, w)
    outs = kr_all_modes(t, factors_for(t, w))
    return reduce(DataFrame.unionByName, [o.select(F.lit(m + 1).cast("long").alias("mode"), "*") for m, o in enumerate(outs)])


for _n in ("w01", "w05"):
    register(f"kr_all_modes_{_n}", lambda s, d, n=_n: _all_modes(s, d, n), " UNION ALL ".join(f"SELECT {m + 1}::BIGINT AS mode, k.* FROM ({_kernel_sql(WORKLOADS[_n], m)}) k" for m in range(WORKLOADS[_n].order)))


def _brute(spark: SparkSession, d: str) -> DataFrame:
    w = WORKLOADS["w12"]
    df = w.build(spark, d)
    t = pack(df, names=w.modes)
    return kr_bruteforce(df, factors_for(t, w), 0, t.shape.lengths)


register("kr_bruteforce_w12", _brute, _kernel_sql(WORKLOADS["w12"], 0))


def _baseline(spark: SparkSession, d: str, n: str, mode: int, kind: str) -> DataFrame:
    w = WORKLOADS[n]
    df = w.build(spark, d)
    t = pack(df, names=w.modes)
    lengths, factors = t.shape.lengths, factors_for(t, w)
    if kind == "coo_morton":
        return baselines.coo_kr(baselines.coo_reorder_morton(df, lengths), factors, mode, lengths)
    if kind.startswith("coo"):
        return baselines.coo_kr(df, factors, mode, lengths, private=kind == "coo_private")
    if kind.startswith("blk"):
        return baselines.blk_kr(baselines.blk_build(df, lengths, super_bits=int(kind[3:])), factors, mode)
    root = (mode + 1) % w.order if kind == "csf_other" else mode
    return baselines.csf_kr(baselines.csf_build(df, lengths, root, tile=16 if kind == "csf_tile" else None), factors, mode)


for _n in ("w01", "w05", "w07"):
    for _kind in ("coo", "coo_private", "coo_morton", "blk10", "blk14", "csf", "csf_tile", "csf_other"):
        for _m in (1, 2) if _n == "w01" else (2,):
            register(f"kr_{_n}_{_kind}_m{_m}", lambda s, d, n=_n, m=_m, k=_kind: _baseline(s, d, n, m - 1, k), _kernel_sql(WORKLOADS[_n], _m - 1))


def _csf_nodes(spark: SparkSession, d: str) -> DataFrame:
    df = WORKLOADS["w01"].build(spark, d)
    return baselines.csf_nodes(baselines.csf_build(df, pack(df).shape.lengths, 0))


register("csf_nodes_w01", _csf_nodes, f"WITH {_coo_cte(WORKLOADS['w01'])} " + " UNION ALL ".join(f"SELECT {k}::BIGINT AS level, count(*) AS nodes FROM (SELECT DISTINCT {keys} FROM coo)" for k, keys in enumerate(("c1", "c1, c3", "c1, c3, c2"))))
_waves = "SELECT c1 >> 10 AS s1, c2 >> 10 AS s2, c3 >> 10 AS s3, count(*) AS n, count(DISTINCT (c1 >> 7, c2 >> 7, c3 >> 7)) AS blocks FROM ({sql}) GROUP BY 1, 2, 3"
register(
    "blk_waves_w02",
    lambda s, d: baselines.blk_waves(baselines.blk_build(df := WORKLOADS["w02"].build(s, d), pack(df).shape.lengths), 0).withColumn("wave", F.col("wave").cast("long")),
    f"SELECT *, row_number() OVER (PARTITION BY s1 ORDER BY s1, s2, s3) AS wave FROM ({_waves.format(sql=WORKLOADS['w02'].sql)})",
)
register(
    "csr_w11",
    lambda s, d: baselines.csr_build(WORKLOADS["w11"].build(s, d)).select("c1", "n", F.array_join(F.transform("cells", lambda c: c["c2"].cast("string")), ",").alias("cols"), F.aggregate("cells", F.lit(0.0), lambda a, c: a + c["val"]).alias("total")),
    f"SELECT c1, count(*) AS n, string_agg(c2::VARCHAR, ',' ORDER BY c2) AS cols, sum(val) AS total FROM ({WORKLOADS['w11'].sql}) GROUP BY c1",
)

# --- algebra


def _vector(spark: SparkSession, length: int, mode: int) -> DataFrame:
    return init_factors(spark, [length] * (mode + 1), 1)[mode].withColumnRenamed("f0", "v")


def _with_shape(n: str, f: Callable) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        df = WORKLOADS[n].build(spark, d)
        return f(spark, df, pack(df).shape.lengths)

    return run


_w1, _w3, _w5 = (WORKLOADS[n].sql for n in ("w01", "w03", "w05"))
_f = lambda m, r: factor_sql(m, f"c{m + 1}", r, 64)
register("ttv_w01", _with_shape("w01", lambda s, df, n: algebra.ttv(df, _vector(s, n[2], 2), 2)), f"SELECT c1, c2, sum(val * {_f(2, 0)}) AS val FROM ({_w1}) GROUP BY c1, c2")
register("ttm_w01", _with_shape("w01", lambda s, df, n: algebra.ttm(df, init_factors(s, n, 4)[0], 0)), f"SELECT c2, c3, {', '.join(f'sum(val * {_f(0, r)}) AS y{r}' for r in range(4))} FROM ({_w1}) GROUP BY c2, c3")
register("inner_w01_w03", lambda s, d: algebra.inner(WORKLOADS["w01"].build(s, d), WORKLOADS["w03"].build(s, d)), f"SELECT sum(a.val * b.val) AS \"inner\" FROM ({_w1}) a JOIN ({_w3}) b USING (c1, c2, c3)")
register("norm_w01", lambda s, d: algebra.norm(WORKLOADS["w01"].build(s, d)), f"SELECT sqrt(sum(val * val)) AS norm FROM ({_w1})")
register("scale_w03", lambda s, d: algebra.scale(WORKLOADS["w03"].build(s, d), 0.5), f"SELECT c1, c2, c3, val * 0.5 AS val FROM ({_w3})")
register("add_w01_w03", lambda s, d: algebra.add(WORKLOADS["w01"].build(s, d), algebra.scale(WORKLOADS["w03"].build(s, d), -1.0)), f"SELECT c1, c2, c3, sum(val) AS val FROM (SELECT * FROM ({_w1}) UNION ALL SELECT c1, c2, c3, -val FROM ({_w3})) GROUP BY c1, c2, c3 HAVING sum(val) <> 0")
register("hadamard_w01_w03", lambda s, d: algebra.hadamard(WORKLOADS["w01"].build(s, d), WORKLOADS["w03"].build(s, d)), f"SELECT c1, c2, c3, a.val * b.val AS val FROM ({_w1}) a JOIN ({_w3}) b USING (c1, c2, c3)")
register("reduce_mode_w05", lambda s, d: algebra.reduce_mode(WORKLOADS["w05"].build(s, d), [0, 3]), f"SELECT c2, c3, sum(val) AS val FROM ({_w5}) GROUP BY c2, c3")
register("slices_w01", lambda s, d: algebra.slice_stats(WORKLOADS["w01"].build(s, d), [0]), f"SELECT c1, count(*) AS n, sum(val) AS total FROM ({_w1}) GROUP BY c1")
register("fibers_w01", lambda s, d: algebra.slice_stats(WORKLOADS["w01"].build(s, d), [0, 1]), f"SELECT c1, c2, count(*) AS n, sum(val) AS total FROM ({_w1}) GROUP BY c1, c2")
register("unfold_w12", _with_shape("w12", lambda s, df, n: unfold(df, 1, n)), f"WITH {_coo_cte(WORKLOADS['w12'])}, l AS (SELECT max(c3) + 1 AS n3 FROM coo) SELECT c2 AS row, c1 * n3 + c3 AS col, val FROM coo, l")
register(
    "cp_eval_w12",
    _with_shape("w12", lambda s, df, n: algebra.cp_eval(df, init_factors(s, n, 4))),
    f"SELECT c1, c2, c3, {' + '.join(f'{_f(0, r)} * {_f(1, r)} * {_f(2, r)}' for r in range(4))} AS model FROM ({WORKLOADS['w12'].sql})",
)
register("merge_w01_w03", _with_shape("w01", lambda s, df, n: unpack(merge(a := pack(df), pack(algebra.scale(df.where("val <= 10"), -1.0), a.shape, a.plan)))), f"SELECT * FROM ({_w1}) WHERE val > 10")


def _khatri(spark: SparkSession, d: str) -> DataFrame:
    """Of the factors of W5's days and hours, with a row for every index that occurs in the events."""
    from .operators.factors import khatri_rao

    w = WORKLOADS["w05"]
    cells = checkpointed(w.build(spark, d).select("c3", "c4").distinct())
    days, hours = (init_factor(spark, 0, 4, m, indices=cells.select(F.col(c).alias("idx")).distinct()) for m, c in enumerate(("c3", "c4")))
    return khatri_rao(days, hours, infer_shape(cells).lengths[1])


register("khatri_rao_small", _khatri, f"WITH {_coo_cte(WORKLOADS['w05'])} SELECT j * (SELECT max(c4) + 1 FROM coo) + k AS idx, {', '.join(f'{factor_sql(0, chr(106), r, 64)} * {factor_sql(1, chr(107), r, 64)} AS f{r}' for r in range(4))} FROM (SELECT DISTINCT c3 AS j FROM coo), (SELECT DISTINCT c4 AS k FROM coo)")


def _gram(spark: SparkSession, d: str) -> DataFrame:
    """Of the part mode's factor, with a row for every part that lineitem has."""
    parts = read_table(spark, d, "lineitem", F.col("l_partkey").alias("idx")).where("idx IS NOT NULL").distinct()
    g = gram(init_factor(spark, 0, 4, 0, indices=parts))
    return spark.createDataFrame([(i, j, float(g[i, j])) for i in range(4) for j in range(4)], "i long, j long, g double")


register("gram_small", _gram, " UNION ALL ".join(f"SELECT {i}::BIGINT AS i, {j}::BIGINT AS j, sum({factor_sql(0, 'x', i, 64)} * {factor_sql(0, 'x', j, 64)}) AS g FROM (SELECT DISTINCT l_partkey AS x FROM lineitem WHERE l_partkey IS NOT NULL)" for i in range(4) for j in range(4)))

_inside = "c1 BETWEEN 100 AND 300 AND c3 BETWEEN 10 AND 20"
register("sel_box_w01", lambda s, d: select_box(packed(s, d, WORKLOADS["w01"]), {0: (100, 300), 2: (10, 20)}), f"SELECT * FROM ({_w1}) WHERE {_inside}")
register("sel_slice_w01", lambda s, d: select_box(packed(s, d, WORKLOADS["w01"]), {1: (7, 7)}), f"SELECT * FROM ({_w1}) WHERE c2 = 7")
register("sel_fiber_w01", lambda s, d: select_box(packed(s, d, WORKLOADS["w01"]), {1: (7, 7), 2: (5, 5)}), f"SELECT * FROM ({_w1}) WHERE c2 = 7 AND c3 = 5")


def _toy(spark: SparkSession, d: str) -> DataFrame:
    """The plan of the small tensor of the table: for every position bit its mode and level, and the masks."""
    lengths = infer_shape(SMALL.build(spark, d)).lengths
    plan, masks, curve = BitPlan.adaptive(lengths), BitPlan.adaptive(lengths).masks(), BitPlan.morton(lengths)
    return spark.createDataFrame([(p, m + 1, level, masks[m], plan.line_length(), curve.line_length()) for p, (m, level) in enumerate(plan.order)], "p long, mode long, level long, mask long, line long, morton_line long")


_line = "(1::BIGINT << (SELECT {bits} FROM bits)::INT)"
register(
    "toy_plan",
    _toy,
    f"WITH {_coo_cte(SMALL)}, {_lengths_cte(SMALL)}, {_plan_cte('adaptive')} SELECT p, (mode + 1)::BIGINT AS mode, level, (sum(1::BIGINT << p::INT) OVER (PARTITION BY mode))::BIGINT AS mask, {_line.format(bits='sum(bits)')} AS line, {_line.format(bits='3 * max(bits)')} AS morton_line FROM plan",
)

#: A tensor of that size, for tests.
TOY = [(1, 0, 0, 1.0), (3, 1, 1, 2.0), (0, 3, 0, 3.0), (2, 2, 1, 4.0), (3, 4, 0, 5.0), (1, 6, 1, 6.0)]


def _toy_encode(spark: SparkSession, d: str) -> DataFrame:
    """The small tensor of the table, packed and decoded."""
    t = packed(spark, d, SMALL)
    return t.df.select("*", *decode_all(t.plan))


register("toy_encode", _toy_encode, f"{_encoded(SMALL)} SELECT pos::BIGINT AS p0, val, c1, c2, c3 FROM line")


def _coverage(spark: SparkSession, d: str) -> DataFrame:
    return coverage(cut(spark, d, WORKLOADS["w01"]).boxes, 1).agg(F.sum(F.col("hi") - F.col("lo") + 1).cast("long").alias("covered"))


register("coverage_w01_m1", _coverage, f"{_segmented(WORKLOADS['w01'])}, {_boxes_sql(WORKLOADS['w01'])}, i AS (SELECT unnest(range((SELECT max(hi1) + 1 FROM boxes))) AS ix) SELECT count(*) AS covered FROM i WHERE (SELECT count(*) FROM boxes WHERE ix BETWEEN lo1 AND hi1) > 1")

# --- decomposition


def _cp(spark: SparkSession, d: str, n: str) -> DataFrame:
    w = WORKLOADS[n]
    t = packed(spark, d, w)
    model = cp_als(t.df, packed_kernel(t), t.shape.lengths, 4, 3)
    return spark.createDataFrame([(w.name, k + 1, float(f)) for k, f in enumerate(model.fits)], "workload string, sweep long, fit double")


register("cp_als_fit_w05", lambda s, d: _cp(s, d, "w05"))
register("cp_als_fit_w12", lambda s, d: _cp(s, d, "w12"))

from .operators import relational  # noqa: E402
from .streaming import cells  # noqa: E402

for _module in (relational, cells):
    QUERIES.update(_module.QUERIES)
    ORACLES.update(_module.ORACLES)
