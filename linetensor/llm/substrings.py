"""Substring dedup by super-k-mer partitioning.

A window is ``WINDOW`` consecutive words of one document. Each window has a minimiser, the least
hash among its runs of three words; consecutive windows with the same minimiser travel together as
one packed string of words, a super-k-mer, to the bucket of that minimiser. Equal windows have equal
minimisers, so each bucket sees all occurrences of its windows. Within a bucket the windows are
sorted by hash, runs of equal hashes are compared word for word, and each run knows its first
document. Words covered by a window that also starts in a document with a smaller id are removed.

Before the shuffle a task keeps each distinct super-k-mer once with the places where it occurs,
delta-packed, so that copies of a passage cost a few bytes each and their words travel once a
batch; a bucket takes the super-k-mers of many minimisers, and rows of a bucket are read in a stream.

Cases: words are cut at ASCII white space and otherwise unchanged. Null and short texts have no
windows and stay. A null id has no order, so its rows neither remove nor lose words. Rows that
repeat an id are one document and remove nothing from each other; ranges are kept by id and text,
so each row loses its own. Input columns travel in a struct, so extra columns cannot clash. An
empty table gives an empty table.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import arrow_map, partitions, sha

WINDOW, CORE = 13, 3
#: Bytes of super-k-mers that a task gathers before it sends them, and buckets for each shuffle partition.
GATHERED, BUCKETS = 12 << 20, 4
#: Odd multipliers for mixing hashes.
MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], np.uint64)


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(zlib.crc32, words), np.uint64, count=len(words))


def minimisers(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each window the place of its minimiser and the minimiser's value."""
    core = np.zeros(len(hashes) - CORE + 1, np.uint64)
    for k in range(CORE):
        core += hashes[k : k + len(core)] * MIX[k]
    core ^= core >> np.uint64(31)
    core *= MIX[0]
    view = np.lib.stride_tricks.sliding_window_view(core, WINDOW - CORE + 1)
    place = view.argmin(axis=1) + np.arange(len(view))
    return place, core[place]


def super_kmers(words: list[bytes]) -> Iterator[tuple[int, int, bytes]]:
    """(first word, minimiser, packed words) of each run of windows that share a minimiser."""
    if len(words) < WINDOW:
        return
    place, value = minimisers(word_hashes(words))
    starts = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
    ends = np.append(starts[1:], len(place)) + WINDOW - 1  # one beyond the last word
    packed = b" ".join(words)
    offsets = np.concatenate([[0], np.cumsum(np.fromiter(map(len, words), np.int64, count=len(words)) + 1)])
    for first, mini, a, b in zip(starts.tolist(), value[starts].tolist(), offsets[starts].tolist(), offsets[ends].tolist(), strict=True):
        yield first, mini, packed[a : b - 1]


class _Sender:
    """Gathers distinct super-k-mers with their places and packs them by bucket."""

    schema = pa.schema([("bucket", pa.int32()), ("texts", pa.binary()), ("places", pa.binary())])

    def __init__(self, buckets: int):
        self.buckets, self.size = buckets, 0
        self.held: dict[bytes, tuple[int, list[int]]] = {}
        self.pack = zstandard.ZstdCompressor(level=5).compress

    def add(self, document: int, mark: int, text: str) -> None:
        for first, mini, packed in super_kmers(text.encode("utf-8", "replace").split()):
            found = self.held.get(packed)
            if found is None:
                self.held[packed] = found = (mini % self.buckets, [])
                self.size += len(packed)
            found[1].extend((document, mark, first))

    def flush(self) -> Iterator[pa.RecordBatch]:
        by: dict[int, list[tuple[bytes, list[int]]]] = {}
        for packed, (bucket, places) in self.held.items():
            by.setdefault(bucket, []).append((packed, places))
        self.held, self.size = {}, 0
        buckets, texts, places = [], [], []
        for bucket, rows in by.items():
            counts = np.array([len(p) // 3 for _, p in rows], np.int64)
            flat = np.array([x for _, p in rows for x in p], np.int64).reshape(-1, 3)
            flat[1:, 0] -= flat[:-1, 0].copy()
            buckets.append(bucket)
            texts.append(self.pack(b"\n".join(t for t, _ in rows)))
            places.append(self.pack(len(rows).to_bytes(8, "little") + counts.tobytes() + np.ascontiguousarray(flat.T).tobytes()))
        if buckets:
            yield pa.RecordBatch.from_arrays([pa.array(buckets, pa.int32()), pa.array(texts, pa.binary()), pa.array(places, pa.binary())], schema=self.schema)


def _unpacked(texts: bytes, places: bytes, unpack) -> tuple[bytes, np.ndarray, np.ndarray]:
    raw = unpack(places)
    n = int.from_bytes(raw[:8], "little")
    counts = np.frombuffer(raw, np.int64, count=n, offset=8)
    flat = np.frombuffer(raw, np.int64, offset=8 + 8 * n).reshape(3, -1).copy()
    flat[0] = np.cumsum(flat[0])
    return unpack(texts), counts, flat


def covered_ranges(rows: list[tuple[bytes, bytes]]) -> tuple[np.ndarray, ...]:
    """(document, mark, first word, end) of the runs of words that a bucket's windows remove."""
    unpack = zstandard.ZstdDecompressor().decompress
    parts = [_unpacked(t, p, unpack) for t, p in rows]
    buffer = b"\n".join(t for t, _, _ in parts)
    counts, flat = np.concatenate([c for _, c, _ in parts]), np.concatenate([f for _, _, f in parts], axis=1)
    words = buffer.split()
    hashes = word_hashes(words)
    raw = np.frombuffer(buffer, np.uint8)
    cuts = np.flatnonzero((raw == 32) | (raw == 10))
    word_starts = np.concatenate([[0], cuts + 1])
    word_ends = np.append(cuts, len(raw))
    text_ends = np.append(np.flatnonzero(raw[cuts] == 10) + 1, len(words)) if len(cuts) else np.array([len(words)])  # in words
    text_starts = np.concatenate([[0], text_ends[:-1]])
    owners = np.repeat(np.arange(len(counts)), counts)
    first_document = np.minimum.reduceat(flat[0], np.concatenate([[0], np.cumsum(counts)[:-1]]))
    n_windows = text_ends - text_starts - WINDOW + 1
    window_text = np.repeat(np.arange(len(counts)), n_windows)
    window_base = np.cumsum(n_windows) - n_windows
    window_word = np.arange(n_windows.sum()) - window_base[window_text] + text_starts[window_text]
    value = np.zeros(len(words) - WINDOW + 1, np.uint64)
    for k in range(WINDOW):
        value = value * MIX[1] + hashes[k : k + len(value)]
    value = value[window_word]
    order = np.argsort(value, kind="stable")
    ranked = value[order]
    heads = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
    group = np.cumsum(np.concatenate([[False], ranked[1:] != ranked[:-1]]))
    group = _told_apart(buffer, order, group, heads, window_word, word_starts, word_ends)
    least = np.full(int(group.max()) + 1, np.iinfo(np.int64).max)
    np.minimum.at(least, group, first_document[window_text[order]])
    earliest = np.empty(len(order), np.int64)
    earliest[order] = least[group]
    low, high = np.minimum.reduceat(earliest, window_base), np.maximum.reduceat(earliest, window_base)
    documents, marks, firsts = flat
    every = documents > high[owners]
    some = np.flatnonzero(~every & (documents > low[owners]))
    out = [np.stack([documents[every], marks[every], firsts[every], firsts[every] + n_windows[owners[every]] + WINDOW - 1])]
    for at in some.tolist():
        text = owners[at]
        here = np.flatnonzero(earliest[window_base[text] : window_base[text] + n_windows[text]] < documents[at])
        runs = np.split(here, np.flatnonzero(np.diff(here) > 1) + 1)
        out.append(np.array([[documents[at], marks[at], firsts[at] + r[0], firsts[at] + r[-1] + WINDOW] for r in runs], np.int64).T)
    return tuple(np.concatenate(out, axis=1))


def _told_apart(buffer: bytes, order, group, heads, window_word, word_starts, word_ends) -> np.ndarray:
    """Groups of equal hashes, parted where the words differ: every member is compared with its group's first."""
    begins, stops = word_starts[window_word[order]], word_ends[window_word[order] + WINDOW - 1]
    head = heads[group]
    members = np.flatnonzero(head != np.arange(len(head)))
    other = np.zeros(len(members), bool)
    for k, (a, b, c, d) in enumerate(zip(begins[members].tolist(), stops[members].tolist(), begins[head[members]].tolist(), stops[head[members]].tolist(), strict=True)):
        other[k] = buffer[a:b] != buffer[c:d]
    if other.any():
        group = group.copy()
        named: dict[tuple[int, bytes], int] = {}
        top = int(group.max())
        for at in members[other].tolist():
            name = (int(group[at]), buffer[begins[at] : stops[at]])
            if name not in named:
                top += 1
                named[name] = top
            group[at] = named[name]
    return group


def removed_ranges(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, mark, ranges) for every document that loses words; ranges of words may overlap."""
    buckets = partitions(df.sparkSession) * BUCKETS
    rows = df.select(F.col(key).cast("long").alias("key"), F.col(text).alias("text")).where("key IS NOT NULL AND text IS NOT NULL")

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sender = _Sender(buckets)
        for batch in batches:
            for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sender.add(k, zlib.crc32(t.encode("utf-8", "replace")), t)
                if sender.size > GATHERED:
                    yield from sender.flush()
        yield from sender.flush()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, at = [], None
        for batch in batches:
            for bucket, texts, places in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and bucket != at:
                    yield out(held)
                    held = []
                at = bucket
                held.append((texts, places))
        if held:
            yield out(held)

    def out(held: list[tuple[bytes, bytes]]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in covered_ranges(held)], names=["key", "mark", "first", "end"])

    packed = arrow_map(rows, send, "bucket int, texts binary, places binary")
    dealt = packed.repartition("bucket").sortWithinPartitions("bucket")
    found = arrow_map(dealt, count, "key long, mark long, first long, end long")
    return found.groupBy("key", "mark").agg(F.collect_list(F.struct("first", "end")).alias("ranges"))


def dedup_substrings(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: ``row`` (its columns), ``kept_text`` (kept words joined by a space), ``n_words`` and ``n_removed``."""
    ranges = removed_ranges(df, key, text)
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row")).withColumn("mark", F.crc32(F.encode(F.coalesce(F.col(f"row.`{text}`"), F.lit("")), "UTF-8")))
    at = (rows[f"row.{key}"].cast("long") == ranges["key"]) & (rows["mark"] == ranges["mark"])
    joined = rows.join(ranges.hint("shuffle_hash"), at, "left").select("row", F.col(f"row.`{text}`").alias("text"), "ranges")
    schema = T.StructType([joined.schema["row"], T.StructField("kept_text", T.StringType()), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept, counts, removed = [], [], []
            for t, ranges in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                words = (t or "").encode("utf-8", "replace").split()
                counts.append(len(words))
                if ranges:
                    edges = np.zeros(len(words) + 1, np.int64)
                    np.add.at(edges, [r["first"] for r in ranges], 1)
                    np.add.at(edges, [r["end"] for r in ranges], -1)
                    stays = np.cumsum(edges[:-1]) == 0
                    words = [words[i] for i in np.flatnonzero(stays).tolist()]
                removed.append(counts[-1] - len(words))
                kept.append(None if t is None else b" ".join(words).decode("utf-8"))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(kept, pa.string()), pa.array(counts, pa.int64()), pa.array(removed, pa.int64())], names=["row", "kept_text", "n_words", "n_removed"])

    return arrow_map(joined, run, schema)


def substring_digest(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    done = dedup_substrings(df, key, text)
    return done.select(F.col(f"row.`{key}`").alias(key), "n_words", "n_removed", sha(F.coalesce("kept_text", F.lit(""))).alias("kept_sha256"))


#: The same by definition.
DIGEST_SQL = r"""
WITH split AS (SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words FROM documents WHERE text IS NOT NULL),
  windows AS (SELECT doc_id, p, array_to_string(words[p:p + 12], ' ') AS content FROM (SELECT doc_id, words, unnest(range(1, len(words) - 11)) AS p FROM split)),
  firsts AS (SELECT content, min(doc_id) AS first FROM windows GROUP BY content HAVING count(DISTINCT doc_id) > 1),
  gone AS (SELECT DISTINCT doc_id, p FROM (SELECT w.doc_id, unnest(range(w.p, w.p + 13)) AS p FROM windows w JOIN firsts f USING (content) WHERE f.first < w.doc_id)),
  single AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS p FROM split),
  kept AS (SELECT s.doc_id, count(*) AS n_words, count(g.p) AS n_removed, string_agg(s.word, ' ' ORDER BY s.p) FILTER (g.p IS NULL) AS text FROM single s LEFT JOIN gone g USING (doc_id, p) GROUP BY s.doc_id)
SELECT d.doc_id, coalesce(k.n_words, 0)::BIGINT AS n_words, coalesce(k.n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(k.text, '')) AS kept_sha256
FROM documents d LEFT JOIN kept k USING (doc_id)
"""
