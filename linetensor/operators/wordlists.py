"""Storage counts of the tensor of documents, words and sources, from lists of places of each word.

Elements are nearly as many as the words of all texts, so they are never dealt out one by one. A task
lists for each word of its texts the places (source and document) that hold it, a few bytes each. The
lists are put in the order of their words, numbered there, and dealt again to cells of 128 words and
32,768 documents. The combinations of coordinates that are nearly as many as the elements lie in one
cell each and are counted there; of the others a cell gives its few keys. A cell has no more elements
than that product for each source of a document, so a word of all documents makes no task long.

A document without number or source has no places, but its words are numbered. Rows that repeat a
document count once.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import distinct_counts
from ..sources.tensors import passing
from .combinations import key_of
from .packed import infer_shape

#: Bits of the words and documents in a cell, which tiles and blocks of 128 divide.
WORD_BITS, DOC_BITS = 7, 15
BLOCK_BITS = 7
#: Bytes of text listed at once, and bytes of lists counted at once where they are several cells.
TEXT_BYTES, CELL_BYTES = 8 << 20, 1 << 20

LISTS = "token string, docs long, places binary"
NUMBERED = "part int, idx long, docs long, places binary, words long, pairs long, top long"
COUNTS = "of string, k1 long, k2 long, k3 long, n long"


def pack_places(values: np.ndarray, first: np.ndarray, real: np.ndarray) -> pa.Array:
    """Lists of increasing numbers as differences in groups of seven bits; first marks where lists start, and what is not real takes no bytes."""
    steps = values.copy()
    steps[1:] -= np.where(first[1:], 0, values[:-1])
    size = real.astype(np.int64)
    for k in range(1, 9):
        size += real & (steps >= 1 << 7 * k)
    starts = np.cumsum(size) - size
    data = np.zeros(int(size.sum()), np.uint8)
    for k in range(int(size.max(initial=0))):
        at = size > k
        data[starts[at] + k] = steps[at] >> 7 * k & 127 | np.where(size[at] > k + 1, 128, 0)
    offsets = np.append(starts[first], len(data)).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(data)])


def unpack_places(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of all lists, and the row of each."""
    offsets = np.frombuffer(lists.buffers()[1], np.int32)[lists.offset : lists.offset + len(lists) + 1].astype(np.int64)
    if offsets[0] == offsets[-1]:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    data = np.frombuffer(lists.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
    ends = np.flatnonzero(data < 128)
    starts = np.append(0, ends[:-1] + 1)
    shifts = 7 * (np.arange(len(data)) - np.repeat(starts, ends - starts + 1))
    steps = np.add.reduceat((data & 127).astype(np.int64) << shifts, starts)
    before = np.searchsorted(ends, offsets - offsets[0])
    row = np.repeat(np.arange(len(lists)), np.diff(before))
    total = np.append(0, np.cumsum(steps))
    return total[1:] - total[before[row]], row


def list_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """LISTS of rows with c1, c3 and text; words are what stands between spaces and line ends."""
    held, size = [], 0
    for batch in batches:
        upto = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy().astype(np.int64))
        at = 0
        while at < batch.num_rows:
            before = upto[at - 1] if at else 0
            end = max(at + (not size), int(np.searchsorted(upto, before + TEXT_BYTES - size, "right")))
            held.append(batch.slice(at, end - at))
            size += upto[end - 1] - before if end > at else TEXT_BYTES
            at = end
            if size >= TEXT_BYTES or at < batch.num_rows:
                yield from _listed(pa.Table.from_batches(held))
                held, size = [], 0
    if held:
        yield from _listed(pa.Table.from_batches(held))


def _listed(rows: pa.Table) -> Iterator[pa.RecordBatch]:
    rows = rows.filter(pc.is_valid(rows["text"])).combine_chunks()
    if not rows.num_rows:
        return
    split = pc.split_pattern(pc.replace_substring(rows["text"].chunk(0), "\n", " "), " ")
    words = split.flatten().dictionary_encode()
    names, code = words.dictionary, words.indices.to_numpy()
    order = pc.array_sort_indices(names).to_numpy()
    rank = np.argsort(order)
    kept = pc.not_equal(names, "").to_numpy(zero_copy_only=False)[code]
    code, row = rank[code[kept]], pc.list_parent_indices(split).to_numpy()[kept]
    del split, words
    if not len(code):
        return

    # Places are numbered from 1 in the order of their documents' cells; 0 stands for none.
    placed = pc.and_(pc.is_valid(rows["c1"]), pc.is_valid(rows["c3"])).to_numpy()
    doc, source = (pc.fill_null(rows[c], 0).to_numpy() for c in ("c1", "c3"))
    docs, place = doc >> DOC_BITS, source << DOC_BITS | doc & (1 << DOC_BITS) - 1
    by = np.lexsort((place, docs, placed))
    new = placed[by]
    new[1:] &= ~placed[by][:-1] | (docs[by][1:] != docs[by][:-1]) | (place[by][1:] != place[by][:-1])
    number = np.empty(len(by), np.int64)
    number[by] = np.cumsum(new)
    docs, place = np.append(0, docs[by][new]), np.append(0, place[by][new])
    cell = np.append(0, 1 + np.unique(docs[1:], return_inverse=True)[1])

    code <<= 32
    code |= number[row]
    del row
    found = np.unique(code)
    code, at = found >> 32, found & (1 << 32) - 1
    first = np.ones(len(found), bool)
    first[1:] = (code[1:] != code[:-1]) | (cell[at[1:]] != cell[at[:-1]])
    yield pa.RecordBatch.from_arrays([names.take(pa.array(order[code[first]])), pa.array(docs[at[first]]), pack_places(place[at], first, at > 0)], ["token", "docs", "places"])


def number_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """NUMBERED of one partition of lists in the order of their words, numbered from 0 in it.

    A batch's first row has its words and pairs of word and source that were not met before, and its greatest
    number of a word with places.
    """
    part, idx, last, carried = TaskContext.get().partitionId(), -1, None, np.zeros(0, np.int64)
    for batch in batches:
        n, tokens = batch.num_rows, batch.column("token")
        if not n:
            continue
        new = np.ones(n, np.int64)
        new[0] = tokens[0].as_py() != last
        new[1:] = pc.not_equal(tokens.slice(1), tokens.slice(0, n - 1)).to_numpy(zero_copy_only=False)
        rows = idx + np.cumsum(new)
        place, row = unpack_places(batch.column("places"))
        pairs = np.unique(rows[row] << 32 | place >> DOC_BITS)
        head = np.zeros((3, n), np.int64)
        head[2] = -1
        head[:, 0] = len(np.setdiff1d(pairs >> 32, carried >> 32)), len(np.setdiff1d(pairs, carried)), pairs[-1] >> 32 if len(pairs) else -1
        idx, last = int(rows[-1]), tokens[n - 1].as_py()
        carried = np.union1d(carried, pairs)
        carried = carried[carried >> 32 == idx]
        columns = [pa.array(np.full(n, part, np.int32)), pa.array(rows), batch.column("docs"), batch.column("places"), *map(pa.array, head)]
        yield pa.RecordBatch.from_arrays(columns, ["part", "idx", "docs", "places", "words", "pairs", "top"])


def count_cells(tile: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """COUNTS of rows in the order of cells: sums n for combinations within a cell, and keys of the others."""
    held, key = [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        cell, docs = (batch.column(c).to_numpy() for c in ("cell", "docs"))
        changes = np.flatnonzero((cell[1:] != cell[:-1]) | (docs[1:] != docs[:-1])) + 1
        cut = int(changes[-1]) if len(changes) else 0
        if cut or key != (cell[0], docs[0]):
            yield from _counted(tile, [*held, batch.slice(0, cut)])
            held = []
        held.append(batch.slice(cut))
        key = cell[-1], docs[-1]
    yield from _counted(tile, held)


def _counted(tile: int, batches: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    if not sum(b.num_rows for b in batches):
        return
    rows = pa.Table.from_batches(batches).combine_chunks()
    cell, docs, idx = (rows[c].to_numpy() for c in ("cell", "docs", "idx"))
    lists = rows["places"].chunk(0)
    changes = np.append(True, (cell[1:] != cell[:-1]) | (docs[1:] != docs[:-1]))
    number, starts = np.cumsum(changes), np.append(np.flatnonzero(changes), len(cell))
    upto = np.append(0, np.cumsum(pc.binary_length(lists).to_numpy().astype(np.int64)))[starts]
    at = 0
    while at < len(starts) - 1:
        end = max(at + 1, int(np.searchsorted(upto, upto[at] + CELL_BYTES, "right")) - 1)
        run = slice(starts[at], starts[end])
        yield _cells(tile, number[run], docs[run], idx[run], lists.slice(run.start, run.stop - run.start))
        at = end


def _cells(tile: int, cell: np.ndarray, docs: np.ndarray, idx: np.ndarray, lists: pa.Array) -> pa.RecordBatch:
    place, row = unpack_places(lists)
    cell, c2, c3, doc = cell[row], idx[row], place >> DOC_BITS, place & (1 << DOC_BITS) - 1
    c1, word = docs[row] << DOC_BITS | doc, c2 & (1 << WORD_BITS) - 1
    within = {
        "c1 c2 c3": (word, doc, c3),
        "c1 t2": (word // tile, doc),
        "c1 c3 t2": (word // tile, doc, c3),
        "c2 t1": (word, doc // tile),
        "c2 c3 t1": (word, doc // tile, c3),
        "b1 b2 b3": (doc >> BLOCK_BITS, c3 >> BLOCK_BITS),
    }
    across = {
        "t2": (c2 // tile,),
        "c3 t2": (c2 // tile, c3),
        "s1 s2 s3": (c1 >> 10, c2 >> 10, c3 >> 10),
        "u1 u2 u3": (c1 >> 14, c2 >> 14, c3 >> 14),
    }
    out = [([name], np.zeros((3, 1), np.int64), [len(np.unique(key_of(cell, *columns)))]) for name, columns in within.items()]
    for name, columns in across.items():
        at = np.unique(key_of(*columns), return_index=True)[1]
        keys = np.zeros((3, len(at)), np.int64)
        keys[: len(columns)] = [c[at] for c in columns]
        out.append(([name] * len(at), keys, [0] * len(at)))
    names, keys, n = zip(*out, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(sum(names, [])), *map(pa.array, np.hstack(keys)), pa.array(sum(n, []), pa.int64())], ["of", "k1", "k2", "k3", "n"])


def word_counts(docs: DataFrame, tile: int) -> tuple[dict[tuple[str, ...], int], tuple[int, ...]]:
    """Distinct combinations of coordinates (c), tiles (t) and blocks (b, s, u) of the tensor, by their sorted names, and its lengths.

    docs: c1, the document's number, c3, its source's, and text. Words are numbered in byte order.
    """
    if (1 << WORD_BITS) % tile:
        raise ValueError(f"a tile of {tile} does not divide {1 << WORD_BITS}")
    spark = docs.sparkSession
    with passing(spark) as keep:
        with passing(spark) as once:
            lists = once(docs.mapInArrow(list_words, LISTS))
            numbered = keep(lists.repartitionByRange("token").sortWithinPartitions("token").mapInArrow(number_words, NUMBERED))
        used = keep(docs.where("c1 IS NOT NULL AND c3 IS NOT NULL").where(F.col("text").rlike("[^ \n]")).select("c1", "c3").distinct())
        return _word_counts(numbered, used, tile)


def _word_counts(numbered: DataFrame, used: DataFrame, tile: int) -> tuple[dict[tuple[str, ...], int], tuple[int, ...]]:
    spark = numbered.sparkSession
    totals = [F.sum("words").alias("words"), F.sum("pairs").alias("pairs"), F.max("top").alias("top")]
    parts = numbered.groupBy("part").agg((F.max("idx") + 1).alias("n"), *totals).orderBy("part").collect()  # a row for each task
    before, shifts, top = 0, [], -1
    for p in parts:
        shifts.append((p.part, before))
        top = before + p.top if p.top >= 0 else top
        before += p.n
    placed = numbered.where(F.octet_length("places") > 0).join(F.broadcast(spark.createDataFrame(shifts, "part int, before long")), "part")
    placed = placed.select((F.col("before") + F.col("idx")).alias("idx"), "docs", "places").withColumn("cell", F.shiftright("idx", WORD_BITS))
    cells = placed.repartition("cell", "docs").sortWithinPartitions("cell", "docs").mapInArrow(partial(count_cells, tile), COUNTS)
    keys = cells.groupBy("of", "k1", "k2", "k3").agg(F.sum("n").alias("n"))
    found = {tuple(r.of.split()): r.n or r.keys for r in keys.groupBy("of").agg(F.count(F.lit(1)).alias("keys"), F.sum("n").alias("n")).collect()}  # a row for each set
    found |= distinct_counts(used.withColumn("t1", F.floor(F.col("c1") / tile)), [("c1",), ("c3",), ("t1",), ("c1", "c3")])
    found |= {("c2",): sum(p.words for p in parts), ("c2", "c3"): sum(p.pairs for p in parts)}
    first, last = infer_shape(used).lengths
    return found, (first, max(top, 0) + 1, last)
