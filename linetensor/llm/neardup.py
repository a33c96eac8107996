"""MinHash near-dedup: improved consistent weighted sampling over TF-IDF shingles, banded and verified.

A text is a weighted set of five-word shingles. The weight is the number of occurrences times an
inverse-document-frequency factor, which falls with the logarithm of the share of documents that
hold the shingle: from one, at a share of ``RARE`` or less, to a half for a shingle of all
documents. Frequencies are exact and counted over all documents, copies included: a sketch of
counters, which never count too little, tells which shingles may be above that share, and those are
then counted one by one. There are at most 1 / RARE times the mean number of shingles of a text,
however many documents there are, and only they travel to the tasks. Consistent weighted samples of these sets agree with the
probability of their weighted Jaccard similarity; they are joined to bands, and documents that
share a band are candidates. With ``BANDS`` bands of ``ROWS`` samples, a pair of similarity 0.8 is
missed once in about 1,300 and one of 0.9 once in half a million. Candidates are verified by exact
weighted Jaccard similarity of 0.8 or more, on 64-bit shingle hashes. Classes are the connected
components of the verified links.

Groups: texts with the same words are one representative from the start, so copies are never
paired. Band groups of up to ``SMALL`` representatives are compared in full. Members of larger
groups first meet ``PIVOTS`` of their group. Then all pairs of different classes that can be
similar are covered among the members of larger groups that still hold several: two similar texts
share one of their rarest shingles, of a fifth of the weight, and have weight enough from the first
such shingle on. Those that share one meet a few of its members first, as long as that joins many,
and all that is still apart is compared in full, in cells of bounded size. No
group is gathered in one task, capped or sampled. The words of a text go to as many tasks as its
candidates need.

Cases: words are runs of letters and digits in lower case; texts of fewer than five words are one
shingle. Null texts and texts without words are like nothing: their class is their own id. A null
id has no class. Rows that repeat an id share one class; equal texts are one class. Very long texts
are hashed in stretches; a task holds the shingles of one text at a time beside those of a batch.
Extra columns, whatever their names, are left alone; empty tables give empty tables. The class id
is the least id of the class, so ties do not matter.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, discard, written
from .decontaminate import WORD

SHINGLE, LEAST = 5, 0.8
BANDS, ROWS = 10, 3
#: Share of documents up to which a shingle is simply rare.
RARE = 1 / 1024
#: Counters in each of the two rows of the sketch that tells what may be frequent; counters that travel in one row; shingles that a task counts at once.
COUNTERS, BLOCK, GATHERED = 1 << 20, 1 << 15, 500_000
#: Members of a group that are all compared, candidates that meet a text in one task.
SMALL, TOGETHER = 12, 256
#: Pivots that a larger group has; share of a weight that rounding may cost.
PIVOTS, SLACK = 3, 1e-5
#: Members that others meet before all are compared; one in so many must be linked by that for another turn of it.
PARTNERS, PAYS = 64, 4
#: Marks that go with a mark, so that a pair that has met at one of them is not made again.
BEFORE = 8
#: Rows of members of groups for which one task is enough.
A_TASK = 50_000
#: Characters that are hashed together, shingles that are sampled together, so that arrays stay in cache; buckets of ids by which texts are sifted before a shuffle.
CHARACTERS, AT_ONCE, SIEVE = 1 << 18, 12_000, 1 << 18
#: How hard the texts of members of groups are compressed.
PACKING = 3
_LEVELS = 4096
_NEGLOG = -np.log((np.arange(_LEVELS) + 0.5) / _LEVELS).astype(np.float32)
_UNIFORM = ((np.arange(_LEVELS) + 0.5) / _LEVELS).astype(np.float32)
_MULTIPLIERS = np.array([int.from_bytes(xxhash.xxh3_64_digest(f"sample {i}".encode()), "big") | 1 for i in range(BANDS * ROWS)], np.uint64)
_MIX, _BASE = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


class _Alphabet:
    """By code point, whether it belongs to words; powers of the base by place in a word. Built once in each process."""

    letters: np.ndarray | None = None
    powers = np.ones(1, np.uint64)

    @classmethod
    def ready(cls) -> np.ndarray:
        if cls.letters is None:
            table = np.zeros(0x110000, bool)
            for run in WORD.finditer("".join(map(chr, range(len(table))))):
                table[run.start() : run.end()] = True
            cls.letters = table
        return cls.letters

    @classmethod
    def power(cls, places: np.ndarray, longest: int) -> np.ndarray:
        if len(cls.powers) < longest:
            cls.powers = np.full(longest + 64, _BASE, np.uint64)
            cls.powers[0] = 1
            cls.powers = cls.powers.cumprod(dtype=np.uint64)
        return cls.powers[places]


def _hashed(lowered: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of texts in lower case, behind one another, and where each text's words begin and end."""
    codes = np.frombuffer("\n".join(lowered).encode("utf-32-le", "surrogatepass"), np.uint32)
    at = np.flatnonzero(_Alphabet.ready()[codes])
    if not len(at):
        return np.zeros(0, np.uint64), np.zeros(len(lowered) + 1, np.int64)
    starts = np.concatenate([[0], np.flatnonzero(np.diff(at) > 1) + 1])
    sizes = np.diff(np.append(starts, len(at)))
    value = (codes[at].astype(np.uint64) + np.uint64(1)) * _MIX
    value ^= value >> np.uint64(29)
    value *= _Alphabet.power(np.arange(len(at)) - np.repeat(starts, sizes), int(sizes.max()))
    value = np.add.reduceat(value, starts)
    value ^= value >> np.uint64(32)
    value *= _MIX
    value ^= value >> np.uint64(29)
    return value, np.searchsorted(at[starts], np.cumsum([0, *(len(x) + 1 for x in lowered)]))


def _stretches(text: str) -> Iterator[str]:
    """A long text in pieces that are cut between words."""
    at = 0
    while len(text) - at > CHARACTERS:
        inside = WORD.match(text, at + CHARACTERS)
        cut = inside.end() if inside else at + CHARACTERS
        yield text[at:cut]
        at = cut
    yield text[at:]


def words_of_all(texts: Iterable[str | None]) -> list[np.ndarray]:
    """The hashes of each text's words."""
    out: list[np.ndarray] = []
    held: list[str] = []
    size = 0

    def flush() -> None:
        value, bounds = _hashed(held)
        out.extend(value[a:b] for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True))

    for text in texts:
        low = (text or "").lower()
        if held and size + len(low) > CHARACTERS:
            flush()
            held, size = [], 0
        if len(low) > CHARACTERS:
            out.append(np.concatenate([_hashed([piece])[0] for piece in _stretches(low)]))
            continue
        held.append(low)
        size += len(low) + 1
    if held:
        flush()
    return out


def word_hashes(text: str | None) -> np.ndarray:
    return words_of_all([text])[0]


def weighted_set(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingles, sorted, and how often each occurs."""
    width = min(SHINGLE, len(hashes))
    value = np.zeros(len(hashes) - width + 1 if width else 0, np.uint64)
    for k in range(width):
        value = (value ^ (value >> np.uint64(29))) * _MIX + hashes[k : k + len(value)]
    return np.unique(value, return_counts=True)


def digest(hashes: np.ndarray) -> tuple[int, int]:
    raw = xxhash.xxh3_128_digest(hashes.tobytes())
    return int.from_bytes(raw[:8], "big", signed=True), int.from_bytes(raw[8:], "big", signed=True)


@dataclass
class Idf:
    """Frequent shingles in order with their factors; every other shingle has factor one."""

    shingles: np.ndarray
    factors: np.ndarray

    @classmethod
    def of(cls, shingles: np.ndarray, counts: np.ndarray, documents: int) -> Idf:
        """From distinct shingles with the number of documents that hold them; rare ones may be left out."""
        floor = rare_count(documents)
        kept = counts > floor
        order = np.argsort(shingles[kept])
        share = np.log(documents / counts[kept][order]) / np.log(documents / floor) if kept.any() else np.zeros(0)
        return cls(shingles[kept][order], (0.5 + 0.5 * share).astype(np.float32))

    def factor(self, shingles: np.ndarray) -> np.ndarray:
        out = np.ones(len(shingles), np.float32)
        if len(self.shingles):
            at = np.searchsorted(self.shingles, shingles)
            at[at == len(self.shingles)] = 0
            found = self.shingles[at] == shingles
            out[found] = self.factors[at[found]]
        return out


def rare_count(documents: int) -> float:
    """Number of documents up to which a shingle is rare: one at least."""
    return max(1.0, documents * RARE)


def weights(shingles: np.ndarray, times: np.ndarray, idf: Idf) -> np.ndarray:
    return times.astype(np.float32) * idf.factor(shingles)


def samples(shingles: np.ndarray, weight: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """sets x samples: numbers for each consistent weighted sample, of the chosen shingle and its quantised weight.

    Sets lie behind one another in shingles and weight, and begin at starts.
    """
    logs = np.log(weight)
    sizes = np.diff(np.append(starts, len(shingles)))
    owners = np.repeat(np.arange(len(starts)), sizes)
    out = np.empty((len(starts), len(_MULTIPLIERS)), np.uint64)
    top = np.uint64(_LEVELS - 1)
    for h, multiplier in enumerate(_MULTIPLIERS):
        x = shingles * multiplier
        x ^= x >> np.uint64(32)
        x *= _MIX
        pick = [(x >> np.uint64(shift) & top).view(np.int64) for shift in (4, 16, 28, 40, 52)]
        r = _NEGLOG[pick[0]]
        r += _NEGLOG[pick[1]]
        beta = _UNIFORM[pick[4]]
        t = np.floor(logs / r + beta)
        c = _NEGLOG[pick[2]]
        c += _NEGLOG[pick[3]]
        score = np.log(c, out=c)
        score -= r * (t - beta + 1)
        least = np.minimum.reduceat(score, starts)
        at = np.flatnonzero(score == least[owners])
        at = at[np.concatenate([[True], owners[at[1:]] != owners[at[:-1]]])]
        out[:, h] = shingles[at] ^ (t[at].astype(np.int64).view(np.uint64) * _MIX)
    return out


def bands(found: np.ndarray) -> np.ndarray:
    """sets x bands: one number for each band of samples."""
    rows = found.reshape(len(found), BANDS, ROWS)
    value = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), rows.shape[:2]).copy()
    for k in range(ROWS):
        value = (value ^ rows[:, :, k]) * _MIX
        value ^= value >> np.uint64(31)
    return value.view(np.int64)


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard of two weighted sets."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    common = float(np.minimum(a[1][i], b[1][j]).sum(dtype=np.float64))
    whole = float(a[1].sum(dtype=np.float64) + b[1].sum(dtype=np.float64)) - common
    return common / whole if whole else 0.0


def _places(shingles: np.ndarray) -> list[np.ndarray]:
    """Of each shingle its counter in either row of the sketch; the second row lies behind the first."""
    shift = np.uint64(64 - (COUNTERS.bit_length() - 1))
    return [((shingles * mix >> shift) + np.uint64(k * COUNTERS)).view(np.int64) for k, mix in enumerate((_MIX, _BASE))]


def _count(rows: DataFrame) -> DataFrame:
    """Written once: a row (key, d1, d2) for each text with words, and rows (block, counts, documents) of each task's sketch."""
    names = ["key", "d1", "d2", "block", "counts", "documents"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.int64()]

    def batch_of(n: int, **columns) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(columns[c], k) if c in columns else pa.nulls(n, k) for c, k in zip(names, kinds, strict=True)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sketch, held, size, documents = np.zeros(2 * COUNTERS, np.uint32), [], 0, 0
        for batch in batches:
            keys, marks = [], []
            for key, hashes in zip(batch.column(0).to_pylist(), words_of_all(batch.column(1).to_pylist()), strict=True):
                if len(hashes):
                    keys.append(key)
                    marks.append(digest(hashes))
                    held.append(weighted_set(hashes)[0])
                    size += len(held[-1])
            documents += len(keys)
            if size > GATHERED:
                _add(sketch, held)
                held, size = [], 0
            yield batch_of(len(keys), key=keys, d1=[a for a, _ in marks], d2=[b for _, b in marks])
        if documents:
            _add(sketch, held)
            pack = zstandard.ZstdCompressor(level=1).compress
            blocks = range(2 * COUNTERS // BLOCK)
            yield batch_of(len(blocks), block=blocks, counts=[pack(sketch[i * BLOCK : (i + 1) * BLOCK].tobytes()) for i in blocks], documents=[documents] * len(blocks))

    return written(arrow_map(rows, run, "key long, d1 long, d2 long, block int, counts binary, documents long"))


def _add(sketch: np.ndarray, sets: list[np.ndarray]) -> None:
    if sets:
        for places in _places(np.concatenate(sets)):
            sketch += np.bincount(places, minlength=len(sketch)).astype(np.uint32)


def _may_be_frequent(counted: DataFrame) -> tuple[np.ndarray, int]:
    """A bit for each counter, whether it is above the rare count, and the number of documents. Every block of counters is summed in one task; the driver gets the bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        held: dict[int, list] = {}
        for batch in batches:
            for block, packed, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                sums = held.setdefault(block, [np.zeros(BLOCK, np.int64), 0])
                sums[0] += np.frombuffer(unpack(packed), np.uint32)
                sums[1] += n
        bits = [np.packbits(counts > rare_count(documents)).tobytes() for counts, documents in held.values()]
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array(bits, pa.binary()), pa.array([n for _, n in held.values()], pa.int64())], names=["block", "bits", "documents"])

    sketches = counted.where("block IS NOT NULL").select("block", "counts", "documents").repartition("block")
    out, documents = np.zeros(2 * COUNTERS // 8, np.uint8), 0
    for row in arrow_map(sketches, run, "block int, bits binary, documents long").collect():
        out[row["block"] * BLOCK // 8 : (row["block"] + 1) * BLOCK // 8] = np.frombuffer(row["bits"], np.uint8)
        documents = row["documents"]
    return out, documents


def _idf(counted: DataFrame, rows: DataFrame) -> Idf:
    """Exact counts of the shingles whose counters allow them to be frequent; the driver gets those that are."""
    bits, documents = _may_be_frequent(counted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        allowed = np.unpackbits(bits).view(bool)
        held, size = [], 0

        def counts() -> pa.RecordBatch:
            shingles, n = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(shingles.view(np.int64)), pa.array(n, pa.int64())], names=["shingle", "n"])

        for batch in batches:
            sets = [weighted_set(hashes)[0] for hashes in words_of_all(batch.column(0).to_pylist())]
            shingles = np.concatenate([*sets, np.zeros(0, np.uint64)])
            first, second = _places(shingles)
            held.append(shingles[allowed[first] & allowed[second]])
            size += len(held[-1])
            if size > GATHERED:
                yield counts()
                held, size = [], 0
        if held:
            yield counts()

    sums = arrow_map(rows.select("text"), run, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n"))
    found = sums.where(F.col("n") > rare_count(documents)).collect()
    return Idf.of(np.array([r["shingle"] for r in found], np.int64).view(np.uint64), np.array([r["n"] for r in found], np.int64), documents)


def _signed(rows: DataFrame, idf: Idf) -> DataFrame:
    """(key, whole, bands) of each text with words; whole is its weight."""

    def signed(keys: list[int], sets: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        starts = np.cumsum([0, *(len(s) for s, _ in sets[:-1])])
        shingles = np.concatenate([s for s, _ in sets])
        weight = weights(shingles, np.concatenate([n for _, n in sets]), idf)
        lists = pa.FixedSizeListArray.from_arrays(pa.array(bands(samples(shingles, weight, starts)).ravel()), BANDS).cast(pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(np.add.reduceat(weight.astype(np.float64), starts)), lists], names=["key", "whole", "bands"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, sets, size = [], [], 0
        for batch in batches:
            for k, hashes in zip(batch.column(0).to_pylist(), words_of_all(batch.column(1).to_pylist()), strict=True):
                if len(hashes):
                    keys.append(k)
                    sets.append(weighted_set(hashes))
                    size += len(sets[-1][0])
                if size > AT_ONCE:
                    yield signed(keys, sets)
                    keys, sets, size = [], [], 0
        if keys:
            yield signed(keys, sets)

    return arrow_map(rows, run, "key long, whole double, bands array<long>")


def _groups(signed: DataFrame) -> DataFrame:
    """(band, key, whole, n): members of bands that more than one representative shares."""
    rows = signed.select("key", "whole", F.explode("bands").alias("band"))
    sizes = rows.groupBy("band").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return rows.join(sizes, "band")


def _alike(one: str, two: str):
    """Whether two weights are near enough for similar texts."""
    return F.least(one, two) >= F.greatest(one, two) * (LEAST * (1 - SLACK))


def _small_pairs(groups: DataFrame) -> DataFrame:
    """All pairs of each group of up to SMALL members whose weights allow it."""
    held = groups.where(F.col("n") <= SMALL).groupBy("band").agg(F.sort_array(F.collect_set(F.struct("key", "whole"))).alias("keys"))
    first = held.select("keys", F.posexplode("keys").alias("at", "a"))
    met = first.select("a", F.explode(F.slice("keys", F.col("at") + 2, F.size("keys"))).alias("b"))
    return met.where(_alike("a.whole", "b.whole") & (F.col("a.key") < F.col("b.key"))).select(F.col("a.key").alias("a"), F.col("b.key").alias("b")).distinct()


def _large(groups: DataFrame, tasks: int) -> DataFrame:
    """Written once: (key, whole, bands) of the members of larger groups, with those groups."""
    large = groups.where(F.col("n") > SMALL)
    return written(large.groupBy("key").agg(F.max("whole").alias("whole"), F.collect_set("band").alias("bands")), tasks)


def _pivot_pairs(large: DataFrame, tasks: int) -> tuple[DataFrame, DataFrame]:
    """Each member of a larger group with each of the group's pivots, as (a: the pivot, b), and the pivots, which are written."""
    rows = large.select("key", "whole", F.explode("bands").alias("band"))
    drawn = F.array(*[F.min(F.struct(F.xxhash64("key", F.lit(k)).alias("o"), F.col("key").alias("pivot"), "whole")) for k in range(PIVOTS)])
    pivots = written(rows.groupBy("band").agg(F.array_distinct(F.transform(drawn, lambda p: F.struct(p["pivot"], p["whole"]))).alias("pivots")), tasks)
    met = rows.join(pivots, "band").select("key", F.explode(F.filter("pivots", lambda p: (p["pivot"] != F.col("key")) & _alike(p["whole"], "whole"))).alias("p"))
    return met.select(F.col("p.pivot").alias("a"), F.col("key").alias("b")).distinct(), pivots


def _open_members(large: DataFrame, classes: DataFrame) -> DataFrame:
    """(key, class) of the members of larger groups that still hold several classes."""
    rows = large.select("key", "bands").join(classes, "key", "left").select("key", F.coalesce("class", "key").alias("class"), F.explode("bands").alias("band"))
    several = rows.groupBy("band").agg(F.min("class").alias("low"), F.max("class").alias("high")).where("low <> high").select("band")
    return rows.join(several, "band", "left_semi").select("key", "class").distinct()


def prefix(shingles: np.ndarray, weight: np.ndarray, factors: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Rarest shingles first, as many as a similar set must share one of; the weight from each of them on, and the whole weight."""
    order = np.lexsort((shingles, -factors))
    rest = weight[order].astype(np.float64)[::-1].cumsum()[::-1]
    n = int(np.count_nonzero(rest >= LEAST * rest[0] * (1 - SLACK)))
    return shingles[order[:n]], rest[:n], float(rest[0])


def _prefixes(rows: DataFrame, idf: Idf) -> DataFrame:
    """(mark, key, rest, whole, before) for the shingles in the prefix of each text; before has the marks just ahead of the mark."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, keys, rests, wholes, before = [], [], [], [], []
            for key, hashes in zip(batch.column(0).to_pylist(), words_of_all(_unpacked(batch.column(1))), strict=True):
                shingles, times = weighted_set(hashes)
                factors = idf.factor(shingles)
                marks, rest, whole = prefix(shingles, times.astype(np.float32) * factors, factors)
                found.append(marks)
                keys.append(np.full(len(marks), key, np.int64))
                rests.append(rest)
                wholes.append(np.full(len(marks), whole))
                signed = marks.view(np.int64).tolist()
                before += [signed[max(0, k - BEFORE) : k] for k in range(len(signed))]
            if found:
                numbers = [pa.array(np.concatenate(x)) for x in (keys, rests, wholes)]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64)), *numbers, pa.array(before, pa.list_(pa.int64()))], names=["mark", "key", "rest", "whole", "before"])

    return arrow_map(rows.select("key", "text"), run, "mark long, key long, rest double, whole double, before array<long>")


def _marked(marks: DataFrame, classes: DataFrame) -> DataFrame:
    """(mark, key, class, rest, whole, before, common, n, others): marks of several classes, with the most common class, and how many members are outside of it."""
    classed = marks.join(classes, "key", "left").withColumn("class", F.coalesce("class", "key"))
    by_class = classed.groupBy("mark", "class").agg(F.count(F.lit(1)).alias("n"))
    sizes = by_class.groupBy("mark").agg(F.sum("n").alias("n"), F.max(F.struct("n", "class")).alias("most")).where("n > most.n")
    return classed.join(sizes.select("mark", F.col("most.class").alias("common"), "n", (F.col("n") - F.col("most.n")).alias("others")), "mark")


def _enough():
    """Whether two texts that first meet at a mark have weight enough from there on."""
    return F.least("rest", "rest_1") * (1 + LEAST) >= (F.col("whole") + F.col("whole_1")) * (LEAST * (1 - SLACK))


def _cover_pairs(marked: DataFrame, sample: int | None = None, turn: int = 0) -> DataFrame:
    """All pairs of different classes that share a mark and have weight enough from there on, unless they met at a mark just ahead.

    Texts of one class are not paired: of each mark's members, those outside of its most common class meet all, in cells of
    up to TOGETHER by TOGETHER members. With a sample, they meet about so many of a mark's members, others each turn.
    """
    cuts = lambda n: F.ceil(n / F.lit(TOGETHER)).cast("int")
    n = F.least("n", F.lit(sample)) if sample else F.col("n")
    held = marked.withColumns({"all": cuts(n), "beside": cuts(F.col("others"))})
    met_by = held.where(F.pmod(F.xxhash64(F.lit(turn), "key"), F.ceil(F.col("n") / F.lit(sample))) == 0) if sample else held
    home = lambda n: F.pmod(F.xxhash64("key"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    one = held.where("class <> common").select("mark", home("beside").alias("i"), every("all").alias("j"), *[F.col(c).alias(f"{c}_1") for c in ("key", "class", "rest", "whole", "before")])
    two = met_by.select("mark", every("beside").alias("i"), home("all").alias("j"), "key", "class", "rest", "whole", "before", "common")
    apart = (F.col("class") != F.col("class_1")) & ((F.col("class") == F.col("common")) | (F.col("key") > F.col("key_1")))
    met = one.join(two, ["mark", "i", "j"]).where(apart & _enough() & ~F.arrays_overlap("before", "before_1"))
    return met.select(F.least("key", "key_1").alias("a"), F.greatest("key", "key_1").alias("b")).distinct()


def _packed(rows: DataFrame) -> DataFrame:
    """(key, text) with the text compressed: members' texts are shuffled several times, and once more for each candidate pair."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=PACKING).compress
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([pack(t) for t in batch.column(1).to_pylist()], pa.binary())], names=["key", "text"])

    return arrow_map(rows.select("key", F.col("text").cast("binary")), run, "key long, text binary")


def _unpacked(texts: pa.Array) -> Iterator[str]:
    unpack = zstandard.ZstdDecompressor().decompress
    return (unpack(t.as_py()).decode() for t in texts)


def _members(groups: DataFrame, rows: DataFrame) -> DataFrame:
    """Written once: the compressed texts of all members of groups. Buckets of their ids, at most SIEVE, sift the rows before the shuffle."""
    ids = groups.select("key").distinct()
    bucket = F.pmod(F.xxhash64("key"), F.lit(SIEVE))
    sifted = rows.join(F.broadcast(ids.select(bucket.alias("bucket")).distinct()), bucket == F.col("bucket"), "left_semi")
    return written(_packed(sifted).join(ids, "key", "left_semi"))


def _verified(pairs: DataFrame, rows: DataFrame, idf: Idf, tasks: int) -> DataFrame:
    """Written once: links (a, b) of the pairs that are similar enough; a's words meet up to TOGETHER candidates in a task."""
    pairs = written(pairs, tasks)
    shares = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / F.lit(TOGETHER)).cast("int").alias("shares"))
    asked = pairs.join(shares, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("shares")).cast("int").alias("share"))
    texts = rows.select(F.col("key").alias("id"), "text")
    right = asked.join(texts, asked["b"] == texts["id"]).select("a", "share", "b", "text")
    left = shares.join(texts, shares["a"] == texts["id"]).select("a", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)).alias("share"), F.lit(None).cast("long").alias("b"), "text")
    dealt = left.unionByName(right).repartition("a", "share").sortWithinPartitions("a", "share", "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, at = [], None
        for batch in batches:
            found = []
            a_all, share_all, b_all = (c.to_pylist() for c in batch.columns[:3])
            for a, share, b, hashes in zip(a_all, share_all, b_all, words_of_all(_unpacked(batch.column(3))), strict=True):
                shingles, times = weighted_set(hashes)
                this = shingles, weights(shingles, times, idf)
                if b is None:
                    own = [*own, this] if at == (a, share) else [this]  # an id may stand for several texts
                    at = a, share
                elif at == (a, share) and max(similarity(one, this) for one in own) >= LEAST:
                    found.append((a, b))
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], names=["a", "b"])

    links = written(arrow_map(dealt, run, "a long, b long"), max(4 * tasks, rows.sparkSession.sparkContext.defaultParallelism))
    discard(pairs)
    return links


def components(links: DataFrame) -> DataFrame:
    """(key, class): the least key of each connected component; labels spread along links and jump to their label's label."""
    tasks = _tasks(2 * links.count())
    both = written(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), tasks)
    held = written(both.groupBy(F.col("a").alias("key")).agg(F.least(F.min("b"), F.first("a")).alias("class")), tasks)
    while True:
        labels = held.select("key", "class")
        near = both.join(labels.withColumnRenamed("key", "b"), "b").groupBy(F.col("a").alias("key")).agg(F.min("class").alias("near"))
        spread = labels.join(near, "key").select("key", F.col("class").alias("before"), F.least("class", "near").alias("next"))
        jumps = labels.select(F.col("key").alias("next"), F.col("class").alias("jump"))
        found = written(spread.join(jumps, "next", "left").select("key", "before", F.coalesce("jump", "next").alias("class")), tasks)
        discard(held)
        held = found
        if found.where("class <> before").isEmpty():
            discard(both)
            return found.select("key", "class")


def _tasks(rows: int) -> int:
    """Tasks that are enough for so many rows."""
    return -(-rows // A_TASK) or 1


def _merged(classes: DataFrame, links: DataFrame, tasks: int) -> DataFrame:
    """The classes after more links, written: only classes that the links join are looked at again."""
    label = lambda end: classes.select(F.col("key").alias(end), F.col("class").alias(f"of_{end}"))
    edges = links.join(label("a"), "a", "left").join(label("b"), "b", "left").select(F.coalesce("of_a", "a").alias("a"), F.coalesce("of_b", "b").alias("b"))
    roots = components(written(edges.where("a <> b").distinct(), tasks))
    fresh = links.select(F.explode(F.array("a", "b")).alias("key")).distinct().join(classes, "key", "left_anti")
    every = classes.unionByName(fresh.withColumn("class", F.col("key")))
    return written(every.join(roots.select(F.col("key").alias("class"), F.col("class").alias("root")), "class", "left").select("key", F.coalesce("root", "class").alias("class")), tasks)


def _linked(pairs: DataFrame, large: DataFrame, texts: DataFrame, idf: Idf, tasks: int) -> DataFrame:
    """(key, class) of all that is linked: by the given pairs first, then by what they leave open in larger groups."""
    classes = components(_verified(pairs, texts, idf, tasks))
    members = written(_open_members(large, classes), tasks)
    n = members.count()
    if not n:
        return classes
    marks = written(_prefixes(texts.join(members.select("key").distinct(), "key", "left_semi").coalesce(max(_tasks(20 * n), 2)), idf))
    tasks = max(tasks, _tasks(marks.count()))
    pays, turn = True, 0
    while pays:
        turn += 1
        marked = written(_marked(marks, classes), tasks)
        outside = marked.where("class <> common").select("key").distinct().count()
        links = _verified(_cover_pairs(marked, PARTNERS, turn), texts, idf, tasks)
        found = links.count()
        pays = found * PAYS >= outside > 0
        if found:
            classes = _merged(classes, links, tasks)
            discard(marked, links)
    marked = written(_marked(marks, classes), tasks) if found else marked
    links = _verified(_cover_pairs(marked), texts, idf, tasks)
    discard(marked, marks, members)
    return classes if links.isEmpty() else _merged(classes, links, tasks)


def find_classes(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, d1, d2, class) of every text with words."""
    rows = df.select(F.col(f"`{key}`").cast("long").alias("key"), F.col(f"`{text}`").alias("text")).where("key IS NOT NULL AND text IS NOT NULL")
    counted = _count(rows)
    idf = _idf(counted, rows)
    copies = counted.where("key IS NOT NULL").select("key", "d1", "d2")
    members = copies.groupBy("d1", "d2").agg(F.min("key").alias("first"))
    chosen = members.select(F.col("first").alias("key")).distinct()
    least = df.sparkSession.sparkContext.defaultParallelism
    signed = written(_signed(rows, idf).join(chosen, "key", "left_semi"), max(_tasks(copies.count()), least))
    groups = written(_groups(signed), max(_tasks(signed.count() * BANDS), least))
    discard(signed)
    tasks = _tasks(groups.count())
    texts, large = _members(groups, rows), _large(groups, tasks)
    pairs, pivots = _pivot_pairs(large, tasks)
    classes = _linked(pairs.union(_small_pairs(groups)).distinct(), large, texts, idf, tasks)
    discard(groups, texts, large, pivots)
    # a representative's id may stand for several texts: all texts of an id go with it
    own = copies.join(members, ["d1", "d2"]).select("key", "d1", "d2", "first")
    return own.join(classes.withColumnRenamed("key", "first"), "first", "left").select("key", "d1", "d2", F.coalesce("class", "first").alias("class"))


def near_duplicates(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: its id and ``class_id``."""
    by_id = find_classes(df, key, text).groupBy("key").agg(F.min("class").alias("class"))
    ids = df.select(F.col(f"`{key}`").alias("id"))
    out = ids.join(by_id, ids["id"].cast("long") == by_id["key"], "left")
    return out.select(F.col("id").alias(key), F.coalesce("class", F.col("id").cast("long")).alias("class_id"))


def without_near_duplicates(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows whose id is the least of its class, with all columns; rows without id or words stay."""
    gone = find_classes(df, key, text).groupBy("key").agg(F.min("class").alias("class")).where("class <> key").select(F.col("key").alias("gone"))
    rows = df.select(F.col(f"`{key}`").cast("long").alias("id"), F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"))
    return rows.join(gone, rows["id"] == gone["gone"], "left_anti").select("row.*")
