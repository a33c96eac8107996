"""A part of the registry against DuckDB on the small tables; the driver compares all of it."""

import pytest
from oracle_harness import ROOT, spark_rows, sql_rows

from linetensor.queries import ORACLES, QUERIES

NAMES = [
    "w01_coo", "w07_encode", "w05_roundtrip", "w05_encode_morton", "segments_w07", "boxes_w01", "overlaps_w05", "conflicts_w02_m1", "flags_w01_m1_interval", "flags_w01_m1_touch", "imbalance_w01", "block_stats_w02",
    "kr_w06_m2_auto", "kr_w06_m3_auto", "kr_w05_m1_order_generic", "kr_w01_m1_order_generic", *[n for n in QUERIES if n.startswith("kr_w07_")],
    "kr_w01_m1_auto", "kr_w01_m1_flagged", "kr_w05_csf_m2", "kr_w05_blk10_m2", "kr_w01_csf_other_m1", "kr_w01_coo_private_m1", "marginals_cube", "asof_events", "scalar_bits", "toy_plan", "toy_encode", "sel_box_w01",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_matches_sql(spark, name):
    assert spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.001")) == sql_rows(ORACLES[name], "sf0.001")


MADE_UP = ["gram_small", "khatri_rao_small", "toy_encode", "toy_plan", "unpivot_factor"]


@pytest.mark.parametrize("name", MADE_UP)
def test_small_queries_follow_the_tables(spark, name, tmp_path):
    """They take their rows from events or lineitem: other tables, other results, and the same by SQL."""
    cut = {"events": "hour(ts) IN (3, 17) AND day(ts) > 4", "lineitem": "l_linenumber < 4 AND l_partkey % 3 = 1 AND quarter(l_shipdate) < 3"}
    frames = {}
    for table, kept in cut.items():
        df = spark.read.parquet(f"{ROOT}/sf0.001/{table}.parquet").where(kept)
        df.coalesce(1).write.parquet(f"{tmp_path}/{table}.parquet")
        frames[table] = df.toArrow()
    got = spark_rows(QUERIES[name](spark, str(tmp_path)))
    assert got == sql_rows(ORACLES[name], "sf0.001", **frames)
    assert got != spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.001"))


@pytest.mark.parametrize("name", ["storage_w05", "compression_summary"])
def test_storage_matches_sql_where_modes_change_places(spark, name):
    """At sf0.001 there are fewer users than hours, at the scale of the declared lengths more."""
    assert spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.001")) == sql_rows(ORACLES[name], "sf0.001")


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
