import random

from hypothesis import given, settings
from hypothesis import strategies as st

from linetensor import measures
from linetensor.functions.bitplan import BitPlan, decode_all, encode, mode_bits

LENGTHS = st.lists(st.integers(1, 1 << 40), min_size=1, max_size=5)


def test_worked_example():
    plan = BitPlan.adaptive((4, 8, 2))
    assert plan.masks() == [10, 52, 1] and plan.groups() == [3, 2, 1] and plan.line_length() == 64
    assert [plan.subspace(q) for q in (1, 2, 3)] == [[4, 4, 2], [4, 2, 2], [2, 2, 2]]
    assert BitPlan.morton((4, 8, 2)).line_length() == 512
    assert measures.metadata_ratio((4, 8, 2), 8) == 3
    assert measures.line_factor((4, 8, 2)) == 8
    assert [plan.encode_int(c) for c in [(1, 0, 0), (3, 1, 1), (0, 3, 0), (2, 2, 1), (3, 4, 0), (1, 6, 1)]] == [2, 15, 20, 25, 42, 51]


@given(LENGTHS, st.randoms())
@settings(max_examples=60)
def test_every_plan_is_a_bijection(lengths, rng):
    for plan in (BitPlan.adaptive(lengths), BitPlan.morton(lengths), BitPlan.rowmajor(lengths)):
        coords = [rng.randrange(n) for n in lengths]
        position = plan.encode_int(coords)
        assert 0 <= position < plan.line_length()
        assert plan.decode_int(position) == coords
        masks = plan.masks()
        assert sum(masks) == (1 << plan.bits) - 1 and all(a & b == 0 for i, a in enumerate(masks) for b in masks[:i])


@given(LENGTHS)
def test_sizes_are_ordered(lengths):
    assert measures.mask_bits(lengths) <= measures.morton_bits(lengths)
    assert sum(mode_bits(lengths)) == BitPlan.adaptive(lengths).bits
    assert measures.metadata_ratio(lengths, 64) >= 1 and measures.metadata_ratio(lengths, 8) >= 1
    assert measures.packed_bytes(lengths, 10) <= measures.coo_bytes(len(lengths), 10)


def test_columns_equal_plain_integers(spark):
    rng = random.Random(1)
    for lengths in [(1, 5), (4, 8, 2), (1 << 31, 1 << 32), (1 << 32, 1 << 32), (1 << 40, 1 << 43, 1 << 43), (7, 7, 7, 1, 300)]:
        plan = BitPlan.adaptive(lengths)
        rows = [[rng.randrange(n) for n in lengths] for _ in range(50)] + [[n - 1 for n in lengths], [0] * len(lengths)]
        names = [f"c{i + 1}" for i in range(len(lengths))]
        df = spark.createDataFrame([tuple(r) for r in rows], ", ".join(f"{n} long" for n in names))
        for impl in ("tables", "bits"):
            done = df.select("*", *encode(plan, names, impl)).select("*", *[c.alias(f"d{i}") for i, c in enumerate(decode_all(plan, impl))]).collect()
            for r in done:
                coords = [r[n] for n in names]
                position = plan.encode_int(coords)
                limbs = [r[p] for p in plan.columns]
                assert sum(v << (63 * (plan.limbs - 1 - i)) for i, v in enumerate(limbs)) == position
                assert [r[f"d{i}"] for i in range(len(lengths))] == coords


def test_published_index_widths():
    assert measures.packed_bits((4_800_000, 1_800_000, 1_800_000), 1, 8) == 72
    assert measures.packed_bits((319_700, 28_200_000, 1_600_000, 731), 1, 8) == 80
    assert measures.packed_bits((6_200, 24, 77, 32), 1, 8) == 32
