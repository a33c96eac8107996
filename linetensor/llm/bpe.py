"""BPE encoding and decoding by a prefix-sharing trie.

For a byte-pair vocabulary in which every merge makes one token, the encoding of a string is
fixed by the last token of each of its prefixes: token ``t`` ends the encoding of ``p`` exactly
if the last token of ``p`` without ``t`` and ``t`` stay apart when they are merged side by side.
So the distinct words of a batch go into a trie, and one depth-first walk extends the last-token
state symbol by symbol: words with a common beginning share all of its work. The trie is held as its
sorted words; each word's branch point is the length of what it shares with the word before, so the
walk keeps one path of states and no nodes.

Cases: a null text reads as the empty text and has no tokens. Strings of added tokens inside a
text become those tokens. Words beyond ``LONG`` bytes share nothing worth storing and walk the
same recurrence along a single path. Rows are independent: repeated rows, ties and extra columns
do not matter, and an empty table gives an empty table.
"""

from __future__ import annotations

import array
import hashlib
import itertools
import json
import re
import unicodedata
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map

#: Symbols of a word beyond which it is not put in the trie; words (also their symbols in all) and pairs that a worker remembers.
LONG, REMEMBERED, SYMBOLS, PAIRS = 200, 250_000, 4_000_000, 150_000
END = "</w>"
#: The contractions that the vocabulary splits off.
SUFFIXES = "'s|'t|'re|'ve|'m|'ll|'d"
#: Scripts whose letters and digits have long been settled; texts beyond them are split by the library's own tables.
SETTLED = [*range(0x0000, 0x0530), *range(0x2010, 0x2028)]
BEYOND = re.compile("[^\0-\u0239\u023b-\u023d\u023f-\u052f\u2010-\u2027]")


def _class(test) -> str:
    return "".join(re.escape(chr(c)) for c in SETTLED if test(chr(c)))


def _word_pattern() -> re.Pattern:
    """Runs of letters, single digits, runs of anything else but white space."""
    letter = _class(lambda c: unicodedata.category(c)[0] == "L")
    digit = _class(lambda c: unicodedata.category(c)[0] == "N")
    space = _class(lambda c: c.isspace() and not "\x1c" <= c <= "\x1f")
    return re.compile(f"{SUFFIXES}|[{letter}]+|[{digit}]|[^{space}{letter}{digit}]+")


SETTLED_WORD = _word_pattern()
PLAIN_WORD = re.compile(rf"{SUFFIXES}|[a-z]+|[0-9]|[^\t\n\x0b\f\r a-z0-9]+")


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte: itself if printable, else the next free one."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    free = itertools.count(256)
    return [chr(b) if b in printable else chr(next(free)) for b in range(256)]


class PrefixTrieEncoder:
    """Encodes words with the merges of one vocabulary file; each worker process builds its own."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        model = spec["model"]
        self.id_of: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_split = re.compile("|".join(re.escape(t) for t in sorted(self.special, key=len, reverse=True)) or r"(?!)")
        self.rank: dict[tuple[str, str], int] = {}
        self.born: dict[str, int] = {}
        self.parts: dict[str, tuple[str, str]] = {}
        for rank, merge in enumerate(model["merges"]):
            left, right = merge if isinstance(merge, list) else merge.split(" ")
            self.rank[left, right] = rank
            self.born[left + right] = rank
            self.parts[left + right] = (left, right)
        self.longest = max(len(t.removesuffix(END)) for t in self.id_of)
        self.inner, self.final = self._lengths(""), self._lengths(END)
        self.apart: dict[tuple[str, str], bool] = {}
        self.bytes = byte_symbols()
        self.of_symbol = {s: b for b, s in enumerate(self.bytes)}
        self.path, self.library = path, None
        self.decoding = decoding_table(self.id_of, self.special)
        self._forget()

    def _forget(self) -> None:
        """Words remembered: a number for each, and where its ids lie in one flat array."""
        self.number: dict[str | int, int] = {}
        self.held = 0
        self.flat, self.starts, self.lengths = array.array("i"), array.array("q"), array.array("q")

    def _remember(self, word: str | int, ids: Iterable[int]) -> None:
        start = len(self.flat)
        self.flat.extend(ids)
        self.held += len(word) if isinstance(word, str) else 1
        self.number[word] = len(self.starts)
        self.starts.append(start)
        self.lengths.append(len(self.flat) - start)

    def _lengths(self, end: str) -> dict[str, tuple[int, ...]]:
        """By the last symbols, three where there are as many: the lengths of tokens that may end so, longest first."""
        by: dict[str, set[int]] = {}
        for token in self.id_of:
            if token.endswith(END) == bool(end):
                symbols = token.removesuffix(end) if end else token
                by.setdefault(symbols[-3:], set()).add(len(symbols))
        return {k: tuple(sorted(by[k].union(*(by.get(k[-n:], ()) for n in (1, 2))), reverse=True)) for k in by}

    def stay_apart(self, left: str, right: str) -> bool:
        """Whether merging the symbols of left and right side by side gives just these two tokens."""
        if len(self.apart) >= PAIRS:
            self.apart.clear()
        born, ends = self.born, (left, right)
        never = len(self.rank)
        a, b, a_used, b_used = left, right, never, never
        result = True
        while True:
            # a is there until it is merged at a_used, b until b_used; a tie goes to the pair further left
            rank = self.rank.get((a, b), never)
            if rank < a_used and rank <= b_used and rank < never:
                result = False
                break
            at, bt = born.get(a, -1), born.get(b, -1)
            if at < 0 and bt < 0:
                break
            if at > bt:
                a, a_used = self.parts[a][1], at
            else:
                b, b_used = self.parts[b][0], bt
        self.apart[ends] = result
        return result

    def _last(self, symbols: str, at: int, lasts: list[str], end: str) -> str:
        """The last token of the first ``at`` symbols; lasts[d] is the last token at depth d."""
        ids, apart = self.id_of, self.apart
        table = self.final if end else self.inner
        for width in (3, 2, 1):
            for n in table.get(symbols[max(0, at - width) : at], ()) if width <= at else ():
                if n > at:
                    continue
                token = symbols[at - n : at] + end
                if token in ids:
                    if n == at:
                        return token
                    before = lasts[at - n]
                    fits = apart.get((before, token))
                    if fits if fits is not None else self.stay_apart(before, token):
                        return token
        raise ValueError("the vocabulary lacks a single byte")

    def encode_words(self, words: Iterable[str]) -> None:
        """Walk the trie of the words (in byte symbols) once, depth first; results are remembered.

        lasts and ids hold, for every depth of the path, the last token and the ids up to there.
        """
        symbols_of, last, id_of = self.bytes, self._last, self.id_of
        rows = [(w if w.isascii() and w.isalnum() else "".join([symbols_of[b] for b in w.encode("utf-8", "replace")]), w) for w in words]
        rows.sort()
        lasts, ids, above = [""], [()], ""
        for symbols, word in rows:
            depth = len(symbols)
            if depth > LONG:
                self._remember(word, self._along(symbols))
                continue
            shared, most = 0, min(len(lasts), depth) - 1
            while shared < most and above[shared] == symbols[shared]:
                shared += 1
            del lasts[shared + 1 :], ids[shared + 1 :]
            for at in range(shared + 1, depth):
                token = last(symbols, at, lasts, "")
                lasts.append(token)
                ids.append((*ids[at - len(token)], id_of[token]))
            token = last(symbols, depth, lasts, END)
            self._remember(word, (*ids[depth - len(token) + len(END)], id_of[token]))
            above = symbols

    def _along(self, symbols: str) -> list[int]:
        """The same recurrence on one long word, whose ids are gathered from the end."""
        lasts = [""]
        for at in range(1, len(symbols)):
            lasts.append(self._last(symbols, at, lasts, ""))
        token, depth = self._last(symbols, len(symbols), lasts, END), len(symbols)
        found = [self.id_of[token]]
        depth -= len(token) - len(END)
        while depth > 0:
            token = lasts[depth]
            found.append(self.id_of[token])
            depth -= len(token)
        return found[::-1]

    def words(self, text: str) -> list[str]:
        """Words of a text without added tokens, normalised."""
        if text.isascii():
            return PLAIN_WORD.findall(text.lower())
        if BEYOND.search(text):
            return self._rare_words(text)
        if not unicodedata.is_normalized("NFC", text):
            return self._rare_words(text)
        return SETTLED_WORD.findall(text.replace("\u03a3", "\u03c3").lower())

    def _rare_words(self, text: str) -> list[str]:
        """Splitting by the library, whose Unicode tables the vocabulary is used with; the merges stay ours."""
        if self.library is None:
            from tokenizers import Tokenizer

            self.library = Tokenizer.from_file(self.path)
        split = self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(text))
        return [bytes([self.of_symbol[c] for c in word]).decode("utf-8", "replace") for word, _ in split]

    def pieces(self, text: str) -> list[str | int]:
        """Words, and the ids of added tokens that stand in the raw text."""
        if not self.special_split.search(text):
            return self.words(text)
        out: list[str | int] = []
        at = 0
        for found in self.special_split.finditer(text):
            out += self.words(text[at : found.start()])
            out.append(self.special[found.group()])
            at = found.end()
        return out + self.words(text[at:])

    def encode_flat(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and where each text's ids end (from 0)."""
        split = [self.pieces(t) for t in texts]
        if len(self.number) > REMEMBERED or self.held > SYMBOLS:
            self._forget()
        fresh = set().union(*split).difference(self.number)
        plain = {w for w in fresh if isinstance(w, str)}
        for number in fresh - plain:
            self._remember(number, (number,))
        self.encode_words(plain)
        words = np.array([0, *map(len, split)]).cumsum()
        at = np.fromiter(map(self.number.__getitem__, itertools.chain.from_iterable(split)), np.int64, count=int(words[-1]))
        lengths, starts, flat = (np.array(x) for x in (self.lengths, self.starts, self.flat))
        lengths = lengths[at] if len(at) else np.zeros(0, np.int64)
        ends = np.concatenate([[0], lengths.cumsum()])
        shift = starts[at] - ends[:-1] if len(at) else np.zeros(0, np.int64)
        ids = flat[np.repeat(shift, lengths) + np.arange(ends[-1])] if len(at) else np.zeros(0, np.int32)
        return ids.astype(np.int32), ends[words]

    def encode_texts(self, texts: list[str]) -> list[list[int]]:
        ids, ends = self.encode_flat(texts)
        return [ids[a:b].tolist() for a, b in itertools.pairwise(ends)]

    def decode(self, ids: Iterable[int]) -> str:
        """Tokens joined by one space: the vocabulary file names no decoder."""
        return " ".join(map(self.decoding.__getitem__, ids))


def decoding_table(id_of: dict[str, int], special: dict[str, int]) -> np.ndarray:
    """Token by id."""
    table = np.full(max([*id_of.values(), *special.values()]) + 1, "", dtype=object)
    for tokens in (id_of, special):
        for token, i in tokens.items():
            table[i] = token
    return table


def decode_flat(table: np.ndarray, ids: np.ndarray, ends: np.ndarray) -> list[str]:
    """The texts of lists of ids that lie behind one another; text k is between ends[k] and ends[k + 1]."""
    tokens = table[ids].tolist()
    return [" ".join(tokens[a:b]) for a, b in itertools.pairwise(ends.tolist())]


_ENCODERS: dict[str, PrefixTrieEncoder] = {}
_TABLES: dict[str, np.ndarray] = {}


def encoder(path: str) -> PrefixTrieEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = PrefixTrieEncoder(path)
    return _ENCODERS[path]


def decoder(path: str) -> np.ndarray:
    """The decoding table alone, which needs no merges."""
    if path not in _TABLES:
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        _TABLES[path] = decoding_table(spec["model"]["vocab"], {t["content"]: t["id"] for t in spec["added_tokens"]})
    return _TABLES[path]


def encode_documents(df: DataFrame, tokenizer_path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: the key and ``ids`` array<int>."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(tokenizer_path)
        for batch in batches:
            ids, ends = own.encode_flat([t or "" for t in batch.column(1).to_pylist()])
            lists = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(ids))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists], names=["key", "ids"])

    rows = df.select(F.col(key).alias("key"), F.col(text).alias("text"))
    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, ids array<int>").withColumnRenamed("key", key)


def decode_documents(df: DataFrame, tokenizer_path: str, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """One row per input row: the key, ``ids`` and ``decoded``; null ids decode to the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = decoder(tokenizer_path)
        for batch in batches:
            rows = batch.column(1).fill_null([]) if batch.column(1).null_count else batch.column(1)
            ends = np.concatenate([[0], rows.value_lengths().to_numpy(zero_copy_only=False).cumsum()]).astype(int)
            texts = decode_flat(table, rows.flatten().to_numpy(zero_copy_only=False), ends)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], names=["key", "ids", "decoded"])

    rows = df.select(F.col(key).alias("key"), F.col(ids).cast("array<int>").alias("ids"))
    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, ids array<int>, decoded string").withColumnRenamed("key", key)


def round_trip_digest(df: DataFrame, tokenizer_path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: n_tokens, ids_sha256 and decoded_sha256, of the ids that the encoder gives and the text that the decoder makes of them.

    Both run in one worker, so that neither ids nor texts travel: the JVM gets the digests.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(tokenizer_path)
        numerals = np.array([str(i) for i in range(len(own.decoding))], dtype=object)
        digest = lambda texts: pa.array([hashlib.sha256(t.encode("utf-8", "replace")).hexdigest() for t in texts], pa.string())
        for batch in batches:
            ids, ends = own.encode_flat([t or "" for t in batch.column(1).to_pylist()])
            counts = pa.array(np.diff(ends).astype(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), counts, digest(decode_flat(numerals, ids, ends)), digest(decode_flat(own.decoding, ids, ends))], names=["key", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = df.select(F.col(key).alias("key"), F.col(text).alias("text"))
    return arrow_map(rows, run, f"key {rows.schema['key'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string").withColumnRenamed("key", key)
