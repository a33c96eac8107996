"""Line dedup by overlapping windows of three lines.

Lines are split at newlines; lines of nothing but blanks are kept and stand in no window. Every
three consecutive lines are hashed to 128 bits, windows that occur more than once are found over
the whole table, and every occurrence but the first by (id, place) marks its three lines; marks of
overlapping windows merge, and marked lines go.

Cases: a null text stays null and has no lines; texts of fewer than three lines stay as they are.
A null id comes first and its rows keep all lines. Rows that repeat an id are told apart by their
own windows: a row loses lines only where its own text has the marked window, and equal rows are
one occurrence. Input columns travel in a struct, so extra columns cannot clash. An empty table
gives an empty table. A window shared by a third of all rows is one group of the aggregate, which
is combined before the shuffle; the join back to its occurrences can be split by Spark.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import arrow_map, sha

WINDOW = 3
#: Fixed value: what a blank line may hold.
BLANKS = " \t\r\f\v"


def _solid(lines: list[str]) -> list[int]:
    return [i for i, line in enumerate(lines) if line.strip(BLANKS)]


def _hash(lines: list[str]) -> int:
    return xxhash.xxh3_128_intdigest("\n".join(lines).encode("utf-8", "replace"))


def _signed(value: int) -> int:
    value &= 0xFFFFFFFFFFFFFFFF
    return value - (1 << 64) if value >> 63 else value


def window_hashes(df: DataFrame, key: str, text: str) -> DataFrame:
    """One row per window: key, place (among the lines that are not blank), h1 and h2."""
    rows = df.select(F.col(key).alias("key"), F.col(text).alias("text")).where(F.col("text").isNotNull())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, places, high, low = [], [], [], []
            for row, t in enumerate(batch.column(1).to_pylist()):
                lines = [line for line in t.split("\n") if line.strip(BLANKS)]
                for i in range(len(lines) - WINDOW + 1):
                    value = _hash(lines[i : i + WINDOW])
                    at.append(row)
                    places.append(i)
                    high.append(_signed(value >> 64))
                    low.append(_signed(value))
            keys = batch.column(0).take(pa.array(at, pa.int64()))
            yield pa.RecordBatch.from_arrays([keys, pa.array(places, pa.int32()), pa.array(high, pa.int64()), pa.array(low, pa.int64())], names=["key", "place", "h1", "h2"])

    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, place int, h1 long, h2 long")


def dedup_lines(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: ``row`` (its columns), ``kept_text``, ``n_lines`` (not blank) and ``n_removed``."""
    windows = window_hashes(df, key, text)
    place = F.struct("key", "place")
    repeated = windows.groupBy("h1", "h2").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("h1", "h2", "first")
    later = windows.join(repeated, ["h1", "h2"]).where(place > F.col("first"))
    marks = later.groupBy("key").agg(F.collect_list(F.struct("place", "h1", "h2")).alias("marks"))
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"))
    joined = rows.join(marks.hint("shuffle_hash"), rows[f"row.{key}"] == marks["key"], "left").select("row", F.col(f"row.`{text}`").alias("text"), "marks")
    schema = T.StructType([joined.schema["row"], T.StructField("kept_text", T.StringType()), T.StructField("n_lines", T.LongType()), T.StructField("n_removed", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept, counts, removed = [], [], []
            for t, marked in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                out, n, gone = without_marked(t, marked)
                kept.append(out)
                counts.append(n)
                removed.append(gone)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(kept, pa.string()), pa.array(counts, pa.int64()), pa.array(removed, pa.int64())], names=["row", "kept_text", "n_lines", "n_removed"])

    return arrow_map(joined, run, schema)


def without_marked(text: str | None, marks: list[dict] | None) -> tuple[str | None, int, int]:
    """The text without the lines of its marked windows, its number of lines, and how many went."""
    if text is None:
        return None, 0, 0
    lines = text.split("\n")
    solid = _solid(lines)
    if not marks:
        return text, len(solid), 0
    gone: set[int] = set()
    for mark in marks:
        at = solid[mark["place"] : mark["place"] + WINDOW]
        if len(at) == WINDOW:
            value = _hash([lines[i] for i in at])
            if _signed(value >> 64) == mark["h1"] and _signed(value) == mark["h2"]:
                gone.update(at)
    return "\n".join(line for i, line in enumerate(lines) if i not in gone), len(solid), len(gone)


def line_digest(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    done = dedup_lines(df, key, text)
    return done.select(F.col(f"row.`{key}`").alias(key), "n_lines", "n_removed", sha(F.coalesce("kept_text", F.lit(""))).alias("kept_sha256"))


#: The rows of documents after this step, as a CTE body over a table {docs}; the same by definition.
KEPT_SQL = r"""
  {p}split AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS n FROM {docs}),
  {p}solid AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY n) - 1 AS place FROM {p}split WHERE trim(line, E' \t\r\f\v') <> ''),
  {p}windows AS (SELECT doc_id, place, line || chr(10) || lead(line, 1) OVER w || chr(10) || lead(line, 2) OVER w AS content FROM {p}solid WINDOW w AS (PARTITION BY doc_id ORDER BY place)),
  {p}ranked AS (SELECT *, row_number() OVER (PARTITION BY content ORDER BY doc_id, place) AS nth FROM {p}windows WHERE content IS NOT NULL),
  {p}gone AS (SELECT DISTINCT doc_id, place + step AS place FROM {p}ranked, (VALUES (0), (1), (2)) AS s(step) WHERE nth > 1),
  {p}remains AS (SELECT a.doc_id, a.n, a.line, b.place, g.place IS NOT NULL AS removed FROM {p}split a LEFT JOIN {p}solid b USING (doc_id, n) LEFT JOIN {p}gone g ON g.doc_id = b.doc_id AND g.place = b.place),
  {p}kept AS (SELECT doc_id, string_agg(line, chr(10) ORDER BY n) FILTER (NOT removed) AS text, count(place) AS n_lines, count(*) FILTER (removed) AS n_removed FROM {p}remains GROUP BY doc_id)
"""

DIGEST_SQL = "WITH " + KEPT_SQL.format(docs="documents", p="") + """
SELECT d.doc_id, coalesce(k.n_lines, 0)::BIGINT AS n_lines, coalesce(k.n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(k.text, '')) AS kept_sha256
FROM documents d LEFT JOIN kept k USING (doc_id)
"""
