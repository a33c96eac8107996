"""Benchmark decontamination by fingerprints of item-sized windows.

For an item of n words, every window of n consecutive words of a document is a candidate (the
whole document, where it is shorter). Windows and items are sets of weighted five-word shingles,
the weight being the number of occurrences. A window is fingerprinted by a 64-bit SimHash of its
weighted shingles; items of the same size are indexed by the blocks of their fingerprints so that
every item within ``RADIUS`` bits is found: some block of two such fingerprints differs by no more
than RADIUS over the number of blocks, and each block is probed with all values that near. Found
pairs are verified by exact weighted Jaccard similarity, and those of 0.8 or more are reported.

A window that shares no shingle with an item has similarity 0, so only windows that hold one of an
item's shingles are fingerprinted; this leaves out nothing that could be reported.

The benchmark is the stated set of queries: its texts go to the tasks in blocks of at most
``BLOCK_BYTES``; a larger benchmark takes one pass over the documents for each block.

Cases: words are runs of letters and digits in lower case; a text or item without words matches
nothing, and texts of fewer than five words are one shingle. Null texts have no words. Items that
repeat are all reported. Rows that repeat an id are searched each on its own and reported once for
each item with the best similarity and the earliest place. Empty tables give an empty table; extra
columns are left alone.
"""

from __future__ import annotations

import itertools
import re
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, rows_out

SHINGLE, LEAST = 5, 0.8
#: Bits by which a fingerprint may differ (over four deviations beyond what a similarity of 0.8 gives), and blocks of a fingerprint.
RADIUS, BLOCKS = 23, 8
#: Bytes of benchmark texts that one pass takes along.
BLOCK_BYTES = 8 << 20
WORD = re.compile(r"[^\W_]+")
_BITS = 64 // BLOCKS


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def shingles(words: list[str]) -> list[str]:
    """Five-word shingles; a shorter text is one shingle, and no words are none."""
    if len(words) < SHINGLE:
        return [" ".join(words)] if words else []
    return [" ".join(words[i : i + SHINGLE]) for i in range(len(words) - SHINGLE + 1)]


def similarity(a: Counter, b: Counter) -> float:
    """Weighted Jaccard: the sum of lesser weights over the sum of greater ones."""
    common = sum(min(n, b[s]) for s, n in a.items() if s in b)
    whole = sum(a.values()) + sum(b.values()) - common
    return common / whole if whole else 0.0


def votes(found: list[str]) -> np.ndarray:
    """shingles x 64: plus or minus one for each bit of a shingle's hash."""
    hashes = np.array([xxhash.xxh3_64_intdigest(s.encode("utf-8", "replace")) for s in found], np.uint64)
    return ((hashes[:, None] >> np.arange(64, dtype=np.uint64)) & np.uint64(1)).astype(np.int32) * 2 - 1


def fingerprints(sums: np.ndarray) -> np.ndarray:
    """SimHash of each row of summed votes."""
    return ((sums > 0).astype(np.uint64) << np.arange(64, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)


def near_values(reach: int) -> list[int]:
    """Differences of a block with at most reach bits."""
    return [sum(1 << b for b in bits) for n in range(reach + 1) for bits in itertools.combinations(range(_BITS), n)]


NEAR = near_values(RADIUS // BLOCKS)


class Index:
    """Items by size: their shingles, and their fingerprints by block."""

    def __init__(self, items: list[tuple[int, str]]):
        self.items: list[tuple[int, int, Counter]] = []
        self.holders: dict[int, dict[int, list[int]]] = {}
        self.blocks: dict[tuple[int, int, int], list[int]] = defaultdict(list)
        self.prints: list[int] = []
        for item, text in items:
            words = words_of(text)
            if not words:
                continue
            number, found = len(self.items), shingles(words)
            self.items.append((item, len(words), Counter(found)))
            held = self.holders.setdefault(min(SHINGLE, len(words)), defaultdict(list))
            for s in set(words_hash(words, SHINGLE).tolist()):
                held[s].append(number)
            mark = int(fingerprints(votes(found).sum(axis=0)[None])[0])
            self.prints.append(mark)
            for block in range(BLOCKS):
                self.blocks[len(words), block, mark >> (block * _BITS) & ((1 << _BITS) - 1)].append(number)
        self.sieves = {}
        for width, held in self.holders.items():
            self.sieves[width] = np.zeros(1 << 20, bool)
            self.sieves[width][[h & 0xFFFFF for h in held]] = True

    def near(self, size: int, mark: int) -> set[int]:
        """Items of the size whose fingerprints are within the radius."""
        found: set[int] = set()
        for block in range(BLOCKS):
            value = mark >> (block * _BITS) & ((1 << _BITS) - 1)
            for change in NEAR:
                found.update(self.blocks.get((size, block, value ^ change), ()))
        return {n for n in found if (self.prints[n] ^ mark).bit_count() <= RADIUS}

    def search(self, text: str | None) -> list[tuple[int, float, int, int]]:
        """(item, similarity, first word, words) of the best window for each item that has one."""
        words = words_of(text)
        if not words or not self.items:
            return []
        places: dict[int, list[int]] = defaultdict(list)
        for width, held in self.holders.items():  # items of fewer than five words are one shingle of their own width
            if width <= len(words):
                marks = words_hash(words, width)
                for at in np.flatnonzero(self.sieves[width][marks & 0xFFFFF]).tolist():
                    for number in held.get(int(marks[at]), ()):
                        places[self.items[number][1]].append(at)
        best: dict[int, tuple[float, int, int]] = {}
        for size, at in places.items():
            for first, last in _stretches(size, min(SHINGLE, size), at, len(words)):
                self._windows(words, size, first, last, best)
        return [(self.items[n][0], *found) for n, found in sorted(best.items())]

    def _windows(self, words: list[str], size: int, first: int, last: int, best: dict) -> None:
        """Fingerprint all windows of the size that start from first to last, and verify what is near."""
        size = min(size, len(words))
        width = min(SHINGLE, size)  # as the items of this size are cut
        found = [" ".join(words[i : i + width]) for i in range(first, last + size - width + 1)]
        inside = size - width + 1
        sums = np.concatenate([np.zeros((1, 64), np.int32), votes(found).cumsum(axis=0)])
        prints = fingerprints(sums[inside:] - sums[:-inside])
        for k, mark in enumerate(prints.tolist()):
            for whole in {size, *([] if size < len(words) else self._longer(size))}:
                for number in self.near(whole, mark):
                    score = similarity(Counter(found[k : k + inside]), self.items[number][2])
                    if score >= LEAST and score > best.get(number, (0.0,))[0]:
                        best[number] = (score, first + k, size)

    def _longer(self, size: int) -> set[int]:
        """Sizes of items longer than a document, which its only window stands for."""
        return {n for _, n, _ in self.items if n > size}


def words_hash(words: list[str], width: int) -> np.ndarray:
    """A number for each run of width words (or of all, if fewer), the same within one process; equal runs have equal numbers."""
    width = min(width, len(words))
    one = np.fromiter(map(hash, words), np.int64, count=len(words))
    value = np.zeros(len(words) - width + 1, np.int64)
    for k in range(width):
        value = value * np.int64(6364136223846793005) + one[k : k + len(value)]
    return value ^ (value >> 29)


def _stretches(size: int, width: int, at: list[int], n: int) -> Iterator[tuple[int, int]]:
    """Ranges of starts of windows that hold one of the places; overlapping ranges are merged."""
    top = max(0, n - size)
    first, last = None, -1
    for place in sorted(at):
        a, b = max(0, min(place + width - size, top)), min(place, top)
        if first is not None and a <= last + 1:
            last = max(last, b)
            continue
        if first is not None:
            yield first, last
        first, last = a, b
    if first is not None:
        yield first, last


def blocks_of(benchmark: DataFrame, item: str = "item_id", text: str = "text", block_bytes: int = BLOCK_BYTES) -> Iterator[list[tuple[int, str]]]:
    """The benchmark's items in blocks of bounded size, one block on the driver at a time."""
    held, size = [], 0
    rows = benchmark.select(F.col(item).alias("item"), F.col(text).alias("text")).where("text IS NOT NULL")
    for row in rows.toLocalIterator():
        weight = len(row["text"].encode("utf-8", "replace")) + 64
        if held and size + weight > block_bytes:
            yield held
            held, size = [], 0
        held.append((row["item"], row["text"]))
        size += weight
    if held:
        yield held


def find_contamination(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per document and item that it holds: key, item, similarity, first_word and n_words of the best window."""
    rows = docs.select(F.col(key).alias("key"), F.col(text).alias("text"))
    kind = rows.schema["key"].dataType.simpleString()
    schema = f"key {kind}, item long, similarity double, first_word long, n_words long"
    passes = [_one_pass(rows, block, schema) for block in blocks_of(benchmark, item, item_text, block_bytes)]
    if not passes:
        return docs.sparkSession.createDataFrame([], schema).withColumnsRenamed({"key": key, "item": item})
    found = passes[0]
    for other in passes[1:]:
        found = found.unionByName(other)
    # rows that repeat an id meet here; there are as many rows as finds
    best = F.max(F.struct("similarity", (-F.col("first_word")).alias("before"), "n_words")).alias("best")
    found = found.groupBy("key", "item").agg(best)
    return found.select(F.col("key").alias(key), F.col("item").alias(item), "best.similarity", (-F.col("best.before")).alias("first_word"), "best.n_words")


def _one_pass(rows: DataFrame, block: list[tuple[int, str]], schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Index(block)
        for batch in batches:
            out = pa.schema([("key", batch.schema.field(0).type), ("item", pa.int64()), ("similarity", pa.float64()), ("first_word", pa.int64()), ("n_words", pa.int64())])
            keys = batch.column(0).to_pylist()
            yield from rows_out(((k, *found) for k, t in zip(keys, batch.column(1).to_pylist(), strict=True) for found in index.search(t)), out)

    return arrow_map(rows, run, schema)


def without_contaminated(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents that hold no item, with all their columns; rows without an id stay."""
    found = find_contamination(docs, benchmark, key, text).select(F.col(key).alias("held")).distinct()
    rows = docs.select(F.col(f"`{key}`").alias("id"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return rows.join(found, rows["id"] == found["held"], "left_anti").select("row.*")
