import math

import numpy as np
import pytest
from oracle_harness import ROOT

from linetensor import measures
from linetensor.functions import sqlapi
from linetensor.operators import baselines
from linetensor.operators.factors import from_numpy, init_factors
from linetensor.operators.kernels import kr, kr_bruteforce
from linetensor.operators.packed import TensorShape, dealt, flag_boundary, flag_from_spare_bit, flag_in_spare_bit, merge, pack, segment, select_box, unpack
from linetensor.plans.choose import choose_by_bytes, choose_resolution, classify_reuse, tensor_class
from linetensor.plans.cpals import cp_als, packed_kernel
from linetensor.queries import TOY
from linetensor.sources import tensors
from linetensor.sources.workloads import WORKLOADS, coo

PUBLISHED = {
    "lbnl": ([1600, 4200, 1600, 4200, 868_100], 1.7e6, "limited"), "nips": ([2500, 2900, 14_000, 17], 3.1e6, "high"), "uber": ([183, 24, 1100, 1700], 3.3e6, "high"), "chicago": ([6200, 24, 77, 32], 5.3e6, "high"),
    "vast": ([165_400, 11_400, 2, 100, 89], 26e6, "high"), "darpa": ([22_500, 22_500, 23.8e6], 28.4e6, "limited"), "enron": ([6000, 5700, 244_300, 1200], 54.2e6, "high"), "nell-2": ([12_100, 9200, 28_800], 76.9e6, "high"),
    "fb-m": ([23.3e6, 23.3e6, 166], 99.6e6, "limited"), "flickr": ([319_700, 28.2e6, 1.6e6, 731], 112.9e6, "limited"), "deli": ([532_900, 17.3e6, 2.5e6, 1400], 140.1e6, "medium"), "nell-1": ([2.9e6, 2.1e6, 25.5e6], 143.6e6, "medium"),
    "amazon": ([4.8e6, 1.8e6, 1.8e6], 1.7e9, "high"), "patents": ([46, 239_200, 239_200], 3.6e9, "high"), "reddit": ([8.2e6, 177_000, 8.1e6], 4.7e9, "high"),
}


@pytest.fixture(scope="module")
def toy(spark):
    return spark.createDataFrame(TOY, "c1 long, c2 long, c3 long, val double")


def rows_of(df):
    return sorted(tuple(r) for r in df.collect())


def dense(df, length, rank):
    out = np.zeros((length, rank))
    for r in df.collect():
        out[r["idx"]] = [r[f"y{k}"] for k in range(rank)]
    return out


def test_toy_segments_boxes_and_kernel(spark, toy):
    t = segment(pack(toy, TensorShape(("i", "j", "k"), (4, 8, 2))), 2)
    boxes = {r.seg: r for r in t.boxes.collect()}
    assert [(boxes[s].n, boxes[s].p0_max - boxes[s].p0_min) for s in (0, 1)] == [(3, 18), (3, 26)]
    assert [tuple(boxes[s])[4:] for s in (0, 1)] == [(0, 3, 0, 3, 0, 1), (1, 3, 2, 6, 0, 1)]
    f = lambda n: from_numpy(spark, np.array([[(x + 2 * r + 1) % 4 + 1 for r in range(2)] for x in range(n)], float))
    factors = [f(4), f(8), f(2)]
    wanted = [[6, 36], [76, 28], [48, 8], [38, 82]]
    for resolve in ("auto", "buffered", "direct", "flagged", "sequential"):
        assert dense(kr(t, factors, 0, resolve), 4, 2).tolist() == wanted, resolve
    for impl in ("array", "long", "arrow"):
        assert dense(kr(t, factors, 0, rank_impl=impl), 4, 2).tolist() == wanted, impl
    assert dense(kr_bruteforce(toy, factors, 0, (4, 8, 2)), 4, 2).tolist() == wanted
    flags = {by: {r["c1"] for r in unpackable(flag_boundary(t, 1, by)).where("boundary").collect()} for by in ("interval", "touch")}
    assert flags["interval"] == {1, 2, 3} and flags["touch"] == {1, 3}
    again = flag_from_spare_bit(flag_in_spare_bit(flag_boundary(t, 1)))
    assert rows_of(unpackable(again)) == rows_of(unpackable(flag_boundary(t, 1)))


def unpackable(t):
    return t.df.select(*t.coords(), "val", "boundary")


def test_rank_chunks_and_more_segments_than_elements(spark, toy):
    t = segment(pack(toy), 20)
    assert t.boxes.count() == 6
    factors = init_factors(spark, t.shape.lengths, 19)
    wanted = dense(kr_bruteforce(toy, factors, 1, t.shape.lengths), t.shape.lengths[1], 19)
    for resolve in ("buffered", "flagged", "direct"):
        assert (dense(kr(t, factors, 1, resolve), t.shape.lengths[1], 19) == wanted).all()


def test_edges_of_construction(spark):
    raw = spark.createDataFrame([(0, 1, 2.0), (0, 1, -2.0), (3, 0, -0.0), (None, 1, 5.0), (2, 2, None), (1, 1, 4.0)], "a long, b long, v double")
    from pyspark.sql import functions as F

    df = coo(raw, [F.col("a"), F.col("b")], F.col("v"))
    assert rows_of(df) == [(1, 1, 4.0)]
    empty = pack(df.where("val > 9"))
    assert empty.shape.lengths == (1, 1) and segment(empty, 4).df.count() == 0
    assert merge(pack(df), pack(df)).df.first()["val"] == 8.0
    big = spark.createDataFrame([((1 << 40) - 1, (1 << 43) - 1, (1 << 43) - 1, 1.0), (0, 5, 7, 2.0)], "c1 long, c2 long, c3 long, val double")
    t = pack(big)
    assert t.plan.bits == 126 and t.plan.limbs == 2 and rows_of(unpack(t)) == rows_of(big)
    assert rows_of(select_box(t, {0: (0, 0)})) == [(0, 5, 7, 2.0)]
    assert select_box(t, {0: (5, 2)}).count() == 0


def test_choices_and_published_classes():
    assert choose_resolution(400, 100) == "direct" and choose_resolution(401, 100) == "buffered"
    assert [classify_reuse(x) for x in (8.1, 8, 5, 4.9)] == ["high", "medium", "medium", "limited"]
    assert choose_by_bytes(1000, 10, 16, 1) == "buffered" and choose_by_bytes(1000, 900, 16, 1) == "direct"
    for name, (lengths, nnz, printed) in PUBLISHED.items():
        assert tensor_class(nnz, lengths, "nearest") == printed, name
    assert tensor_class(140.1e6, PUBLISHED["deli"][0]) == "high"  # 8.10 by the printed rule


def test_plans(spark):
    w = WORKLOADS["w01"]
    t = segment(pack(w.build(spark, f"{ROOT}/sf0.001")), 4)
    factors = init_factors(spark, t.shape.lengths, 16)
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert text(kr(pack(w.build(spark, f"{ROOT}/sf0.001")), factors, 0, "direct")).count("SortMergeJoin") == 0
    assert "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint,l_quantity:double,l_shipdate:timestamp_ntz>" in text(w.build(spark, f"{ROOT}/sf0.001"))
    assert "PushedFilters: [IsNotNull(l_quantity), LessThanOrEqual(l_quantity,10.0)" in text(WORKLOADS["w03"].build(spark, f"{ROOT}/sf0.001"))
    parts = dealt(t).df.groupBy("seg", "p0").count()
    assert text(parts).count("Exchange") == text(t.df).count("Exchange") + 1  # the deal itself; none for the groups


def test_sources_round_trip(spark, toy, tmp_path):
    t = pack(toy)
    t.count()
    tensors.write_packed(t, f"{tmp_path}/packed", 2)
    again = tensors.read_packed(spark, f"{tmp_path}/packed")
    assert again.plan == t.plan and again.nnz == 6 and rows_of(unpack(again)) == rows_of(toy)
    tensors.write_tns(toy, f"{tmp_path}/tns")
    assert rows_of(tensors.read_tns(spark, f"{tmp_path}/tns", 3)) == rows_of(toy)
    for kind in ("csv", "json", "orc", "parquet"):
        tensors.write_coo(toy, f"{tmp_path}/{kind}", kind)
        assert rows_of(tensors.read_coo(spark, f"{tmp_path}/{kind}", kind, 3)) == rows_of(toy)


def test_sql_surface(spark, toy):
    t = pack(toy, TensorShape(("i", "j", "k"), (4, 8, 2)))
    sqlapi.register(spark, t.plan, "toy")
    sqlapi.register_table_functions(spark)
    tensors.register_views(spark, "toy", toy, t, init_factors(spark, t.shape.lengths, 2))
    assert [r[0] for r in spark.sql("SELECT lin_encode_toy(c1, c2, c3) p FROM coo_toy ORDER BY p").collect()] == [2, 15, 20, 25, 42, 51]
    assert rows_of(spark.sql("SELECT lin_decode_toy_1(p0), lin_decode_toy_2(p0), lin_decode_toy_3(p0), val FROM packed_toy")) == rows_of(toy)
    assert [tuple(r) for r in spark.sql("SELECT * FROM bit_plan(array(4, 8, 2)) ORDER BY position").collect()][:3] == [(0, 3, 0), (1, 1, 0), (2, 2, 0)]
    assert spark.sql("SELECT * FROM morton_plan(array(4, 8, 2))").count() == 9


def test_trees_and_blocks_count_everything(spark):
    df = WORKLOADS["w05"].build(spark, f"{ROOT}/sf0.001").cache()
    lengths = pack(df).shape.lengths
    n = df.count()
    for tree in baselines.csf_build_all(df, lengths):
        nodes = [r.nodes for r in baselines.csf_nodes(tree).orderBy("level").collect()]
        assert nodes[-1] == n and nodes == sorted(nodes)
        assert baselines.csf_level(tree, 0).count() == nodes[0]
    blocks = baselines.blk_blocks(baselines.blk_build(df, lengths))
    assert blocks.agg({"n": "sum"}).first()[0] == n
    df.unpersist()


def als_numpy(x, factors, sweeps):
    """The same alternation on a dense array."""
    fits = []
    for sweep in range(sweeps):
        for m in range(x.ndim):
            product = None
            for k, f in enumerate(factors):
                if k != m:
                    product = f if product is None else np.einsum("ir,jr->ijr", product, f).reshape(-1, f.shape[1])
            system = np.prod([f.T @ f for k, f in enumerate(factors) if k != m], axis=0)
            new = np.moveaxis(x, m, 0).reshape(x.shape[m], -1) @ product @ np.linalg.pinv(system)
            w = np.linalg.norm(new, axis=0) if sweep == 0 else np.maximum(np.abs(new).max(axis=0), 1)
            factors[m] = new / w
        model = np.einsum("r,ir,jr,kr->ijk", w, *factors)
        fits.append(1 - np.linalg.norm(x - model) / np.linalg.norm(x))
    return fits


def test_decomposition_finds_a_planted_model_as_numpy_does(spark):
    rng = np.random.default_rng(2)
    a, b, c = (rng.random((n, 2)) + 0.1 for n in (6, 5, 4))
    x = np.einsum("ir,jr,kr->ijk", a, b, c)
    df = spark.createDataFrame([(i, j, k, float(x[i, j, k])) for i in range(6) for j in range(5) for k in range(4)], "c1 long, c2 long, c3 long, val double")
    t = pack(df)
    start = [rng.random((n, 2)) + 0.5 for n in (6, 5, 4)]
    model = cp_als(t.df, packed_kernel(t), t.shape.lengths, 2, 4, tol=0, factors=[from_numpy(spark, f) for f in start])
    assert np.allclose(model.fits, als_numpy(x, [f.copy() for f in start], 4), atol=1e-6)
    assert all(p <= q + 1e-9 for p, q in zip(model.fits, model.fits[1:], strict=False)) and model.fits[-1] > 0.9
    other = cp_als(df, lambda fs, m: baselines.coo_kr(df, fs, m, (6, 5, 4)), (6, 5, 4), 2, 2, tol=0, factors=[from_numpy(spark, f) for f in start])
    tree = cp_als(df, lambda fs, m: baselines.csf_kr(baselines.csf_build(df, (6, 5, 4), m), fs, m), (6, 5, 4), 2, 2, tol=0, factors=[from_numpy(spark, f) for f in start])
    assert np.allclose(other.fits, model.fits[:2], atol=1e-9) and np.allclose(tree.fits, model.fits[:2], atol=1e-9)


def test_measures():
    assert measures.roofline(100.0, 10.0, 50.0, 20.0) == 25.0
    assert measures.speedup(10, 2) == 5 and measures.speedup(10, None) is None
    assert measures.kernel_work(10, 3, 16, 1, 4) == (480, 10 * (16 + 256) + 512)
    assert math.isclose(measures.comparison_model(1024, 1), 10240)
    assert measures.mode_variation([1.0, 3.0]) == 3


def test_long_modes_get_factor_rows_only_where_they_occur(spark):
    from linetensor.operators.factors import init_factor
    from linetensor.plans.choose import choose_delivery

    every = {r.idx: tuple(r) for r in init_factor(spark, 50, 3, 2).collect()}
    some = init_factor(spark, 1 << 60, 3, 2, indices=spark.createDataFrame([(7,), (49,)], "idx long")).collect()
    assert [tuple(r) for r in some] == [every[7], every[49]]
    assert choose_delivery(1 << 40, 16, 1000) == "prefetch" and choose_delivery(1 << 40, 16) == "shuffle" and choose_delivery(1000, 16, 10) == "broadcast"


def test_boundary_by_cells_is_that_of_the_intervals(spark):
    from linetensor.operators.packed import with_boundary

    runs = [(0, 3), (5, 5), (9, 4000), (4010, 4010)]
    rows = spark.createDataFrame([(i,) for i in range(5000)], "idx long")
    got = with_boundary(rows, spark.createDataFrame(runs, "lo long, hi long"), 5000, 8).collect()
    assert {r.idx: r.boundary for r in got} == {i: any(a <= i <= b for a, b in runs) for i in range(5000)} and len(got) == 5000


def test_storage_levels_follow_the_declared_order(spark):
    df = spark.createDataFrame([(a, b, (a * b) % 3, 1.0) for a in range(4) for b in range(40)], "c1 long, c2 long, c3 long, val double")
    lengths = (4, 40, 3)
    measured = measures.storage_bytes(df, lengths, by=(40, 3, 4))  # levels as if mode 2 were the shortest
    assert measured["csf"] != measures.storage_bytes(df, lengths)["csf"]
    nodes = lambda *keys: df.select(*keys).distinct().count()
    trees = [("c1", "c2", "c3"), ("c2", "c3", "c1"), ("c3", "c2", "c1")]
    assert measured["csf"] == sum(measures.tree_bytes([nodes(*path[: k + 1]) for k in range(3)], 160) for path in trees)
    assert measured["packed"] == measures.packed_bytes(lengths, 160)
