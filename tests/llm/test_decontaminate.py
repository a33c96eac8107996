import itertools
import random
from collections import Counter

import numpy as np
from harness import ROOT

from linetensor.llm import decontaminate as d
from linetensor.llm.registry import QUERIES


def brute(docs, items):
    out = {}
    for doc, text in docs:
        words = d.words_of(text)
        for item, t in items:
            wanted = d.words_of(t)
            if not words or not wanted:
                continue
            size = min(len(wanted), len(words))
            target = Counter(d.shingles(wanted))
            if not any(f" {s} " in f" {' '.join(words)} " for s in target):
                continue
            for i in range(len(words) - size + 1):
                score = d.similarity(Counter(d.shingles(words[i : i + size])), target)
                if score >= d.LEAST and score > out.get((doc, item), (0, 0))[0]:
                    out[doc, item] = (score, i)
    return out


def test_blocks_find_everything_within_the_radius():
    rng = random.Random(2)
    index = d.Index([(i, " ".join(f"w{rng.randrange(10**6)}" for _ in range(20))) for i in range(30)])
    for number, mark in enumerate(index.prints):
        for bits in (0, 1, 8, 16, d.RADIUS):
            other = mark
            for b in rng.sample(range(64), bits):
                other ^= 1 << b
            assert number in index.near(20, other)


def test_query_matches_brute_force(spark):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{ROOT}/sf0.001/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{ROOT}/sf0.001/benchmark.parquet").collect()]
    got = {(r.doc_id, r.item_id): (r.similarity, r.first_word) for r in QUERIES["op3_decontamination"](spark, f"{ROOT}/sf0.001").collect()}
    assert got == brute(docs, items) and got


def test_changed_passages_match_brute_force():
    rng = random.Random(4)
    words = [f"w{i}" for i in range(400)]
    items = [(i, " ".join(rng.choices(words, k=rng.choice([3, 5, 14, 40, 60])))) for i in range(25)]
    docs = []
    for i, (_, text) in enumerate(items * 6):
        held = text.split()
        for _ in range(i // 25 % 4):
            held[rng.randrange(len(held))] = "new"
        if i % 3 == 0:
            held.insert(rng.randrange(len(held)), "more")
        docs.append((i, " ".join(rng.choices(words, k=rng.randrange(0, 40)) + held + rng.choices(words, k=rng.randrange(0, 9)))))
    index = d.Index(items)
    got = {(doc, f[0]): (f[1], f[2]) for doc, text in docs for f in index.search(text)}
    assert got == brute(docs, items)
    assert len(got) > 40


def test_cases_and_several_passes(spark):
    docs = spark.createDataFrame([(1, "alpha beta gamma delta epsilon zeta eta", 0), (2, None, 0), (3, "", 0), (None, "ALPHA, beta. gamma! delta epsilon zeta eta", 0), (1, "x alpha beta gamma delta epsilon zeta eta", 0), (4, "one two", 0), (5, "word " * 60_000, 0)], "doc_id long, text string, item_id int")
    items = spark.createDataFrame([(7, "alpha beta gamma delta epsilon zeta eta"), (8, None), (9, ""), (10, "one two"), (11, "alpha beta gamma delta epsilon zeta eta")], "item_id long, text string")
    for block_bytes in (d.BLOCK_BYTES, 100):
        got = {(r.doc_id, r.item_id): (r.similarity, r.first_word, r.n_words) for r in d.find_contamination(docs, items, block_bytes=block_bytes).collect()}
        assert got == {(1, 7): (1.0, 0, 7), (1, 11): (1.0, 0, 7), (None, 7): (1.0, 0, 7), (None, 11): (1.0, 0, 7), (4, 10): (1.0, 0, 2)}
    left = d.without_contaminated(docs, items)
    assert sorted((r.doc_id is None, r.doc_id) for r in left.collect()) == [(False, 2), (False, 3), (False, 5), (True, None)]
    assert left.columns == docs.columns
    assert d.find_contamination(docs.limit(0), items).count() == 0
    assert d.find_contamination(docs, items.limit(0)).count() == 0


def test_fingerprints_of_windows():
    words = [f"a{i % 7}" for i in range(30)]
    found = d.shingles(words)
    sums = np.concatenate([np.zeros((1, 64), np.int32), d.votes(found).cumsum(axis=0)])
    for i, n in itertools.product(range(3), (4, 9)):
        assert d.fingerprints((sums[i + n] - sums[i])[None])[0] == d.fingerprints(d.votes(found[i : i + n]).sum(axis=0)[None])[0]


def test_short_items_in_a_row_are_found(spark):
    docs = spark.createDataFrame([(1, "no no no no", 0), (2, "x a b c d y", 0), (3, "a b x c", 0)], "doc_id long, text string, held int")
    items = spark.createDataFrame([(1, "no no no"), (2, "a b c"), (3, "b c d"), (4, "x")], "item_id long, text string")
    found = {(r.doc_id, r.item_id) for r in d.find_contamination(docs, items).collect()}
    assert found == {(1, 1), (2, 2), (2, 3), (2, 4), (3, 4)}
    assert d.without_contaminated(docs, items).count() == 0
