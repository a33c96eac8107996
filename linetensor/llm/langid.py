"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. The likelihood of a
word is the sum over all its segmentations into pieces, by a forward pass; a text's is the product
over its words. Probabilities come from expectation maximisation: the expected piece counts of
every training word, over all its segmentations, by a forward and backward pass.

Training counts the words of all training documents by language, combined in each task and then
by a shuffle, and keeps only piece counts: vocabulary times languages, which bounds the model
that goes to the driver and to the tasks, whatever the size of the corpus.

Cases: a null text, or one without letters, is ``und`` with score 0, and so is every text where
nothing could be learned. Letters that the vocabulary lacks share one unknown piece. Words beyond
``STRETCH`` letters are cut into stretches. Ties go to the language that sorts first. Rows that
repeat, or repeat an id, are predicted each on its own; extra columns are left alone; an empty
table gives an empty table.
"""

from __future__ import annotations

import itertools
import re
import sys
import unicodedata
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, small_batches, written

WORD = re.compile(r"[^\W\d_]+")
#: Numerals such as superscripts, fractions and Roman ones, which the pattern would take for letters. Those of the first
#: plane make a class that is looked up by a bitmap; with any beyond, every character would be compared with them one by one.
_NUMERALS = [c for c in map(chr, range(0x80, sys.maxunicode + 1)) if c.isalnum() and unicodedata.category(c) in ("No", "Nl")]
NUMERALS, FAR_NUMERALS = (re.compile("[" + "".join(c for c in _NUMERALS if (c > "\uffff") == far) + "]+") for far in (False, True))
FAR = re.compile("[\U00010000-\U0010ffff]")
#: Longest piece used, letters after which a word is cut, words counted or remembered in a task at once.
LONGEST, STRETCH, HELD = 8, 30, 200_000
#: Rounds of expectation maximisation, and what is added to every piece count.
ROUNDS, ADDED = 2, 0.1
#: The vocabulary's mark of a word's start; a multiplier for hashing letters.
START, MULTIPLIER = "▁", np.uint64(0x9E3779B97F4A7C15)
UNDECIDED = "und"


def words_of(text: str) -> list[str]:
    low = text.lower()
    if not low.isascii():
        if NUMERALS.search(low):
            low = NUMERALS.sub(" ", low)
        if FAR.search(low):
            low = FAR_NUMERALS.sub(" ", low)
    return WORD.findall(low)


class Pieces:
    """The vocabulary's lower-case pieces of letters, found by hash for whole arrays of words."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        names = {model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))}
        self.names = sorted(p for p in names if len(p) <= LONGEST and p == p.lower() and (body := p.removeprefix(START)) == "".join(WORD.findall(body)) and p)
        self.unknown = len(self.names)
        by_length: dict[int, list[int]] = defaultdict(list)
        for i, name in enumerate(self.names):
            by_length[len(name)].append(i)
        self.tables = {}
        for n, ids in by_length.items():
            hashes = self._hash(np.array([[ord(c) for c in self.names[i]] for i in ids], np.uint64))
            order = np.argsort(hashes)
            self.tables[n] = hashes[order], np.array(ids)[order]

    @staticmethod
    def _hash(letters: np.ndarray) -> np.ndarray:
        value = np.zeros(letters.shape[:-1], np.uint64)
        for k in range(letters.shape[-1]):
            value = value * MULTIPLIER + letters[..., k] + np.uint64(1)
        return value

    def lattice(self, letters: np.ndarray) -> dict[int, np.ndarray]:
        """By piece length: for each word and start the piece's number, or -1; single letters fall back to the unknown piece."""
        out = {}
        value = np.zeros(letters.shape, np.uint64)
        for n in range(1, min(LONGEST, letters.shape[1]) + 1):
            places = letters.shape[1] - n + 1
            value = value[:, :places] * MULTIPLIER + letters[:, n - 1 :] + np.uint64(1)
            if n in self.tables:
                hashes, ids = self.tables[n]
                at = np.searchsorted(hashes, value).clip(max=len(hashes) - 1)
                found = np.where(hashes[at] == value, ids[at], -1)
            else:
                found = np.full(value.shape, -1)
            out[n] = np.where(found < 0, self.unknown, found) if n == 1 else found
        return out


_PIECES: dict[str, Pieces] = {}


def pieces(path: str) -> Pieces:
    if path not in _PIECES:
        _PIECES[path] = Pieces(path)
    return _PIECES[path]


def stretches(word: str) -> list[str]:
    return [START + word] if len(word) <= STRETCH else [(START if i == 0 else "") + word[i : i + STRETCH] for i in range(0, len(word), STRETCH)]


def _by_length(words: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Words of one length at a time: their places, and their letters as numbers."""
    groups: dict[int, list[int]] = defaultdict(list)
    for i, word in enumerate(words):
        groups[len(word)].append(i)
    for n, at in groups.items():
        letters = np.frombuffer("".join(words[i] for i in at).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(at), n)
        yield np.array(at), letters.astype(np.uint64)


def forward(lattice: dict[int, np.ndarray], table: np.ndarray, n: int) -> np.ndarray:
    """alpha[word, place, language]: the sum over segmentations of the word's first letters. table's last row is for no piece."""
    words = lattice[1].shape[0]
    alpha = np.zeros((words, n + 1, table.shape[1]))
    alpha[:, 0] = 1
    for end in range(1, n + 1):
        for size in range(1, min(end, LONGEST) + 1):
            alpha[:, end] += alpha[:, end - size] * table[lattice[size][:, end - size]]
    return alpha


def log_likelihoods(words: list[str], own: Pieces, table: np.ndarray) -> np.ndarray:
    """words x languages: the logarithm of each word's probability, summed over its segmentations."""
    cut = [stretches(w) for w in words]
    owner = np.repeat(np.arange(len(words)), [len(c) for c in cut])
    flat = list(itertools.chain.from_iterable(cut))
    out = np.zeros((len(words), table.shape[1]))
    for at, letters in _by_length(flat):
        ends = forward(own.lattice(letters), table, letters.shape[1])[:, -1]
        np.add.at(out, owner[at], np.log(np.maximum(ends, 1e-300)))
    return out


def expected_counts(words: list[str], counts: np.ndarray, own: Pieces, column: np.ndarray) -> np.ndarray:
    """Expected number of each piece in these words of one language, over all segmentations."""
    total = np.zeros(own.unknown + 2)
    cut = [stretches(w) for w in words]
    weight = np.repeat(counts, [len(c) for c in cut])
    for at, letters in _by_length(list(itertools.chain.from_iterable(cut))):
        n = letters.shape[1]
        lattice = own.lattice(letters)
        alpha = forward(lattice, column[:, None], n)[:, :, 0]
        beta = np.zeros((len(at), n + 1))
        beta[:, n] = weight[at] / np.maximum(alpha[:, n], 1e-300)
        for start in range(n - 1, -1, -1):
            for size in range(1, min(n - start, LONGEST) + 1):
                ids = lattice[size][:, start]
                flow = column[ids] * beta[:, start + size]
                beta[:, start] += flow
                total += np.bincount(np.where(ids < 0, len(total) - 1, ids), weights=flow * alpha[:, start], minlength=len(total))
    return total[:-1]


class Model:
    """Learned languages, their log priors, and piece probabilities (pieces, unknown, none) x languages."""

    def __init__(self, languages: list[str], priors: np.ndarray, table: np.ndarray):
        self.languages, self.priors, self.table = languages, priors, table


def _table(counts: np.ndarray) -> np.ndarray:
    smoothed = counts + ADDED
    return np.vstack([smoothed / smoothed.sum(axis=0), np.zeros((1, counts.shape[1]))])


def count_words(df: DataFrame, text: str = "text", lang: str = "lang") -> DataFrame:
    """(lang, word, n) over all rows that have a language; tasks combine their counts before the shuffle."""
    rows = df.select(F.col(lang).cast("string").alias("lang"), F.col(text).alias("text")).where(F.col("lang").isNotNull() & F.col("text").isNotNull())

    def flush(held: dict[str, Counter]) -> pa.RecordBatch:
        langs, words, counts = [], [], []
        for language, counter in held.items():
            langs += [language] * len(counter)
            words += counter.keys()
            counts += counter.values()
        return pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(words, pa.string()), pa.array(counts, pa.int64())], names=["lang", "word", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, Counter] = defaultdict(Counter)
        for batch in batches:
            for language, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held[language].update(words_of(t))
            if sum(map(len, held.values())) > HELD:
                yield flush(held)
                held = defaultdict(Counter)
        yield flush(held)

    return arrow_map(rows, run, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def train(df: DataFrame, vocabulary_path: str, text: str = "text", lang: str = "lang", rounds: int = ROUNDS) -> Model:
    """Fit the piece probabilities of every language in df; df holds the training documents only."""
    spark = df.sparkSession
    words = written(count_words(df, text, lang))
    known = {r["lang"]: r["n"] for r in words.groupBy("lang").agg(F.sum("n").alias("n")).collect()}
    languages = sorted(known)
    own = pieces(vocabulary_path)
    if not languages:
        return Model([], np.zeros(0), np.zeros((own.unknown + 2, 0)))
    priors = np.log(np.array([known[x] for x in languages], float) / sum(known.values()))
    model = Model(languages, priors, _table(np.ones((own.unknown + 1, len(languages)))))
    for _ in range(rounds):
        model.table = _table(_expect(words, vocabulary_path, model))
    small_batches(spark)
    return model


def _expect(words: DataFrame, vocabulary_path: str, model: Model) -> np.ndarray:
    """One pass over the counted words: expected piece counts, pieces x languages."""
    place = {x: i for i, x in enumerate(model.languages)}
    table = model.table

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pieces(vocabulary_path)
        total = np.zeros((own.unknown + 1, len(place)))
        for batch in batches:
            by: dict[str, tuple[list, list]] = defaultdict(lambda: ([], []))
            for language, word, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                by[language][0].append(word)
                by[language][1].append(n)
            for language, (some, counts) in by.items():
                total[:, place[language]] += expected_counts(some, np.array(counts, float), own, table[:, place[language]])
        piece, column = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(piece.astype(np.int32)), pa.array(column.astype(np.int32)), pa.array(total[piece, column])], names=["piece", "language", "n"])

    small_batches(words.sparkSession, 20_000)
    found = words.mapInArrow(run, "piece int, language int, n double").groupBy("piece", "language").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros((table.shape[0] - 1, len(place)))
    counts[found["piece"], found["language"]] = found["n"]
    return counts


def predict(df: DataFrame, model: Model, vocabulary_path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: the key, lang_pred and score (the probability of that language among those learned)."""
    rows = df.select(F.col(key).alias("key"), F.col(text).alias("text"))
    languages, priors, table = model.languages, model.priors, model.table

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pieces(vocabulary_path)
        number: dict[str, int] = {}
        logs = np.zeros((0, len(languages)))
        for batch in batches:
            texts = [words_of(t or "") for t in batch.column(1).to_pylist()]
            if len(number) > HELD:
                number, logs = {}, logs[:0]
            fresh = list(set().union(*texts).difference(number))
            if fresh and languages:
                number.update(zip(fresh, range(len(number), len(number) + len(fresh)), strict=True))
                logs = np.concatenate([logs, log_likelihoods(fresh, own, table)])
            found, scores = [], []
            for words in texts:
                if not words or not languages:
                    found.append(UNDECIDED)
                    scores.append(0.0)
                    continue
                total = logs[np.fromiter(map(number.__getitem__, words), np.int64, count=len(words))].sum(axis=0) + priors
                best = int(total.argmax())
                found.append(languages[best])
                scores.append(float(1 / np.exp(total - total[best]).sum()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.string()), pa.array(scores, pa.float64())], names=["key", "lang_pred", "score"])

    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, lang_pred string, score double").withColumnRenamed("key", key)


def held_out(key: str, folds: int, fold: int):
    """Whether a row is in the held-out fold by the checksum of its id; a null id is not."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % folds == fold, F.lit(False))


def identify(docs: DataFrame, vocabulary_path: str) -> DataFrame:
    """Train on the documents that are not held out and predict all."""
    model = train(docs.where(~held_out("doc_id", 4, 2)), vocabulary_path)
    done = predict(docs, model, vocabulary_path)
    return done.select("doc_id", held_out("doc_id", 4, 2).alias("held_out"), "lang_pred", "score")
