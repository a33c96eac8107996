import math

import numpy as np
import public_tokenizers
import pytest
from harness import ROOT

from linetensor.llm import langid
from linetensor.llm.registry import QUERIES

PATH = public_tokenizers.path("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def own():
    return langid.pieces(PATH)


def segmentations(word, names):
    if not word:
        yield []
    for n in range(1, min(len(word), langid.LONGEST) + 1):
        if word[:n] in names or n == 1:
            for rest in segmentations(word[n:], names):
                yield [word[:n], *rest]


def test_forward_and_counts_match_all_segmentations(own):
    rng = np.random.default_rng(1)
    table = langid._table(rng.random((own.unknown + 1, 2)) * 10)
    number = {p: i for i, p in enumerate(own.names)}
    words = ["the", "ñandú", "straße", "ж", "thention"]
    logs = langid.log_likelihoods(words, own, table)
    counts = sum(langid.expected_counts([w], np.array([2.0]), own, table[:, 1]) for w in words)
    brute = np.zeros(own.unknown + 1)
    for w, got in zip(words, logs, strict=True):
        ways = [[number.get(p, own.unknown) for p in way] for way in segmentations(langid.START + w, number)]
        for k in range(2):
            chances = [math.prod(table[i, k] for i in way) for way in ways]
            assert math.isclose(got[k], math.log(sum(chances)), rel_tol=1e-9)
        for way, chance in zip(ways, chances, strict=True):
            for i in way:
                brute[i] += 2 * chance / sum(chances)
    assert np.allclose(counts, brute)


def test_long_words_are_cut(own):
    table = langid._table(np.ones((own.unknown + 1, 1)))
    assert np.isfinite(langid.log_likelihoods(["a" * 5000], own, table)).all()


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{ROOT}/sf0.01/documents.parquet")
    rows = QUERIES["op2_language_id"](spark, f"{ROOT}/sf0.01").join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert len(rows) == docs.count()
    tested = [r for r in rows if r.held_out]
    assert len(tested) > 100
    assert sum(r.lang == r.lang_pred for r in tested) / len(tested) > 0.98
    assert all(0 <= r.score <= 1 for r in rows)


def test_cases(spark):
    rows = [(0, "the cat and the dog", "en"), (1, "le chat et le chien", "fr"), (3, None, "en"), (4, "", None), (5, "123 ###", "xx"), (None, "the dog", None), (6, "the", None), (6, "the", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    done = langid.identify(df, PATH)
    got = [(r.doc_id, r.lang_pred) for r in done.collect()]
    assert sorted(got, key=repr) == sorted([(0, "en"), (1, "fr"), (3, "und"), (4, "und"), (5, "und"), (None, "en"), (6, "en"), (6, "en")], key=repr)
    assert langid.identify(df.limit(0), PATH).count() == 0
    assert {r.lang_pred for r in langid.identify(df.where("lang is null"), PATH).collect()} == {"und"}


def test_only_letters_are_words():
    assert langid.words_of("\u00b2 \u00bd \u2167 123 _ ?!") == []
    assert langid.words_of("m\u00b2 Stra\u00dfe\u2167x \u00c5") == ["m", "stra\u00dfe", "x", "\u00e5"]


def test_numerals_of_both_planes_are_no_letters_and_cost_little():
    """A class with characters beyond the first plane is compared one by one, so those have a pattern of their own."""
    assert langid.words_of("x² ½ Ⅷabc \U00010107ab a\U00010108b") == ["x", "abc", "ab", "a", "b"]
    assert max(langid.NUMERALS.pattern) <= "\uffff" < min(langid.FAR_NUMERALS.pattern[1:-2])
