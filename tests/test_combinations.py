"""Numbers of distinct combinations from dealt groups, against plain sets and SQL."""

import glob
import random
import time

import pyarrow as pa
import pytest
from oracle_harness import ROOT, spark_rows, sql_rows

from linetensor import measures
from linetensor.operators import combinations
from linetensor.operators.combinations import combination_counts, pack_combinations, plan_deals
from linetensor.queries import ORACLES, QUERIES
from linetensor.sources.tensors import DROP_SHUFFLES

W8 = (900_000, 1_200_000, 60_000, 2500, 3)


def storage_sets(lengths, by, tile=64):
    """The sets that the storage model asks for."""
    asked, size = [], {"c": 1, "t": tile, "b": 1 << 7, "s": 1 << 10, "u": 1 << 14}

    def counts_of(sets):
        asked.extend(sorted({tuple((int(n[1:]) - 1, size[n[0]]) for n in s) for s in sets}))
        return {tuple(sorted(s)): 1 for s in sets}

    measures.storage_model(counts_of, lengths, by)
    return asked


def elements(seed=3, n=3000):
    """One index of the second mode has half of the elements; coordinates are below zero, or more than 63 bits together."""
    rng = random.Random(seed)
    return [*{(rng.randrange(-2000, 9000), rng.choice([5, rng.randrange(1 << 40)]), rng.randrange(-3, 3), rng.randrange(1 << 30)) for _ in range(n)}]


@pytest.mark.parametrize("tile", [64, 48, 200])
def test_counts_are_those_of_plain_sets(spark, monkeypatch, tile):
    monkeypatch.setattr(combinations, "BUCKET_BITS", 4)
    rows = elements()
    df = spark.createDataFrame(rows, "c1 long, c2 long, c3 long, c4 long").repartition(5)
    lengths = tuple(max(r[m] for r in rows) + 1 for m in range(4))
    sets = storage_sets(lengths, None, tile)
    assert combination_counts(df, sets, lengths) == [len({tuple(r[m] // size for m, size in s) for r in rows}) for s in sets]
    assert combination_counts(df.limit(0), sets, lengths) == [0] * len(sets)


def test_few_groups_with_few_bytes_have_all_sets_of_w8():
    """Grouping sets had a row of more than 20 columns for each of 35 sets."""
    sets = storage_sets(W8, (1500, 2000, 100, 2500, 3))
    deals = plan_deals(sets, W8)
    assert sorted(k for d in deals for k, _ in d.sets) == list(range(len(sets))) and len(sets) > 30 and len(deals) < 10
    rng = random.Random(1)
    n = 50_000
    batch = pa.RecordBatch.from_arrays([pa.array([rng.randrange(x) for _ in range(n)]) for x in W8], [f"c{m + 1}" for m in range(5)])
    packed = [b for out in pack_combinations(deals, 16, iter([batch])) for b in out.column("packed").to_pylist()]
    assert sum(map(len, packed)) < 40 * n


def test_flags_are_numbered_as_in_sql_where_an_item_has_no_order(spark, tmp_path):
    """The first flag is only in items without an order."""
    items = spark.read.parquet(f"{ROOT}/sf0.001/lineitem.parquet").selectExpr("* EXCEPT (l_returnflag)", "CASE WHEN l_orderkey % 7 = 0 THEN 'A' ELSE l_returnflag || 'x' END AS l_returnflag")
    orders = spark.read.parquet(f"{ROOT}/sf0.001/orders.parquet").where("o_orderkey % 7 <> 0")
    items.coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    orders.coalesce(1).write.parquet(f"{tmp_path}/orders.parquet")
    frames = {"lineitem": items.toArrow(), "orders": orders.toArrow()}
    for name in ("w08_coo", "storage_w08"):
        assert spark_rows(QUERIES[name](spark, str(tmp_path))) == sql_rows(ORACLES[name], "sf0.001", **frames)


@pytest.mark.parametrize("name", ["storage_w09", "storage_w06"])
def test_storage_leaves_neither_rows_nor_shuffles(spark, name):
    """compression_summary goes through twelve tensors; what one of them needed is not on disk with the next."""
    folder = spark.conf.get("spark.checkpoint.dir").removeprefix("file://")
    written = lambda: set(glob.glob(f"{folder}/tensor-*"))
    shuffles = lambda: {f.getName() for f in spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager().getAllFiles()) if f.getName().endswith(".data")}
    rows, before = written(), shuffles()
    setting = spark.conf.get(DROP_SHUFFLES)
    got = spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.001"))
    assert got == sql_rows(ORACLES[name], "sf0.001")
    assert written() == rows and spark.conf.get(DROP_SHUFFLES) == setting
    until = time.time() + 20
    while (left := shuffles() - before) and name == "storage_w09" and time.time() < until:
        time.sleep(0.2)
    assert name != "storage_w09" or not left
