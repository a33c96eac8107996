"""Storage counts of documents, words and sources from lists of places, against plain sets and SQL."""

import random
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest
from oracle_harness import ROOT, spark_rows, sql_rows

from linetensor.operators import wordlists
from linetensor.queries import ORACLES, QUERIES

TILE = 64
TYPES = "c1 long, c3 long, text string"


def documents(seed=5, n=300):
    """Rows with repeated and missing numbers, missing sources and texts, in several cells of words and documents."""
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(900)] + ["é", "中文", "a\tb", "\U0001f600", "￮", "Z", "~"]
    rows = []
    for i in range(n):
        text = rng.choice(["", " ", "\n \n"]) + rng.choice([" ", "\n", "  \n"]).join(["the", *rng.sample(words, rng.randrange(40))])
        rows.append([i * 331, i % 3 * 60, text])
    rows[7][0] = rows[8][0] = rows[6][0]
    rows[8][1] = rows[6][1]
    rows[20:23] = [[4, 0, None], [5, 0, " \n"], [6, 0, ""]]
    rows[30][0], rows[31][1] = None, None
    rows[30][2], rows[31][2] = "0first of all", "a only-here w1"
    return [*map(tuple, rows), rows[50]]


def plain(rows):
    """The numbers of distinct combinations, by sets, and the lengths."""
    split = [(c1, c3, [w for w in text.replace("\n", " ").split(" ") if w]) for c1, c3, text in rows if text is not None]
    number = {w: i for i, w in enumerate(sorted({w for *_, words in split for w in words}, key=str.encode))}
    elements = {(c1, number[w], c3) for c1, c3, words in split if c1 is not None and c3 is not None for w in words}
    of = {"c": lambda x: x, "t": lambda x: x // TILE, "b": lambda x: x >> 7, "s": lambda x: x >> 10, "u": lambda x: x >> 14}
    counts = lambda s: len({tuple(of[k[0]](e[int(k[1]) - 1]) for k in s) for e in elements})
    return counts, tuple(max(x) + 1 for x in zip(*elements, strict=True))


def test_counts_are_those_of_plain_sets(spark):
    rows = documents()
    got, lengths = wordlists.word_counts(spark.createDataFrame(rows, TYPES).repartition(5), TILE)
    counts, expected = plain(rows)
    assert lengths == expected and len(got) == 16
    assert got == {s: counts(s) for s in got}


def test_small_batches_and_cells(monkeypatch):
    """Words, cells and lists that go on in the next batch count once."""
    rows = documents(11)
    monkeypatch.setattr(wordlists, "TEXT_BYTES", 700)
    monkeypatch.setattr(wordlists, "CELL_BYTES", 50)
    monkeypatch.setattr(wordlists, "TaskContext", SimpleNamespace(get=lambda: SimpleNamespace(partitionId=lambda: 3)))
    cut = lambda t, n: [b for at in range(0, t.num_rows, n) for b in t.slice(at, n).combine_chunks().to_batches()]
    table = pa.table({k: pa.array(x, t) for k, x, t in zip(("c1", "c3", "text"), zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.string()), strict=True)})
    lists = pa.Table.from_batches(wordlists.list_words(iter(cut(table, 9))))
    numbered = pa.Table.from_batches(wordlists.number_words(iter(cut(lists.sort_by("token"), 7))))
    counts, lengths = plain(rows)
    assert numbered["words"].to_numpy().sum() == counts(("c2",)) and numbered["pairs"].to_numpy().sum() == counts(("c2", "c3"))
    assert numbered["top"].to_numpy().max() + 1 == lengths[1]
    cells = numbered.append_column("cell", pa.array(numbered["idx"].to_numpy() >> wordlists.WORD_BITS)).sort_by([("cell", "ascending"), ("docs", "ascending")])
    out = pa.Table.from_batches(wordlists.count_cells(TILE, iter(cut(cells.select(["idx", "docs", "places", "cell"]), 7)))).to_pylist()
    for name in {r["of"] for r in out}:
        of = [r for r in out if r["of"] == name]
        assert counts(tuple(name.split())) == (sum(r["n"] for r in of) or len({(r["k1"], r["k2"], r["k3"]) for r in of})), name


def test_places_come_back():
    values = np.array([0, 127, 128, 1 << 20, 5, 5 + (1 << 55), 99, 3], np.int64)
    first = np.array([1, 0, 0, 0, 1, 0, 1, 1], bool)
    lists = wordlists.pack_places(values, first, np.arange(8) != 6)
    got, row = wordlists.unpack_places(lists.slice(1))
    assert got.tolist() == [5, 5 + (1 << 55), 3] and row.tolist() == [0, 0, 2]
    assert wordlists.unpack_places(lists)[0].tolist() == [v for i, v in enumerate(values.tolist()) if i != 6]


def test_storage_with_missing_sources_matches_sql(spark, tmp_path):
    """Words of documents without a source are numbered, and have no elements."""
    rows = [(c1, text, None if c3 is None else f"s{c3}") for c1, c3, text in documents(3) if c1 is not None]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    df.repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    assert spark_rows(QUERIES["storage_w06"](spark, str(tmp_path))) == sql_rows(ORACLES["storage_w06"], "sf0.001", documents=df.toArrow())


def test_storage_does_not_deal_out_elements(spark):
    """Shuffled bytes stay below 30 for each element, of which there are nearly as many as words."""
    written = lambda: spark.sparkContext._jsc.sc().statusStore().executorList(False).apply(0).totalShuffleWrite()
    before = written()
    found = {r.format: r.bytes for r in QUERIES["storage_w06"](spark, f"{ROOT}/sf0.01").collect()}
    elements = found["coo"] // 32
    assert 0 < written() - before < 30 * elements


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_storage_matches_sql(spark, sf):
    assert spark_rows(QUERIES["storage_w06"](spark, f"{ROOT}/{sf}")) == sql_rows(ORACLES["storage_w06"], sf)
