import random
from collections import defaultdict

import numpy as np
from harness import ROOT, spark_rows, sql_rows

from linetensor.llm import substrings
from linetensor.llm.registry import ORACLES, QUERIES


def test_query_matches_sql(spark):
    name = "op4_substring_dedup"
    assert spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.01")) == sql_rows(ORACLES[name], "sf0.01")


def brute(rows):
    """(kept, removed) per row by the definition."""
    first = defaultdict(lambda: 1 << 60)
    split = [(k, (t or "").encode().split()) for k, t in rows]
    for k, w in split:
        if k is not None:
            for i in range(len(w) - 12):
                first[tuple(w[i : i + 13])] = min(first[tuple(w[i : i + 13])], k)
    out = []
    for k, w in split:
        gone = {i + j for i in range(len(w) - 12) if k is not None and first[tuple(w[i : i + 13])] < k for j in range(13)}
        out.append((b" ".join(x for i, x in enumerate(w) if i not in gone).decode(), len(gone)))
    return out


def test_random_passages_match_brute_force(spark):
    rng = random.Random(7)
    passages = [[rng.choice("ab") for _ in range(30)], ["x"] * 40, [f"é{i}" for i in range(60)], ["the", "of"] * 20]
    rows = []
    for i in range(120):
        words = []
        for _ in range(rng.randrange(4)):
            p = rng.choice(passages)
            a = rng.randrange(len(p))
            words += p[a : a + rng.randrange(35)] + [f"w{rng.randrange(50)}" for _ in range(rng.randrange(20))]
        rows.append((rng.choice([i, i // 2, None]) if i % 9 == 0 else i, rng.choice([" ", "\n", "\t "]).join(words)))
    rows += [(500, None), (501, ""), (502, "z " * 13), (502, "z " * 13), (503, "z " * 30_000)]
    df = spark.createDataFrame([(k, t, n) for n, (k, t) in enumerate(rows)], "doc_id long, text string, n_words int")
    done = {r.row.n_words: r for r in substrings.dedup_substrings(df).collect()}
    assert len(done) == len(rows)
    for n, (kept, gone) in enumerate(brute(rows)):
        assert ((done[n].kept_text or ""), done[n].n_removed) == (kept, gone), n
    assert substrings.dedup_substrings(df.limit(0)).count() == 0


def test_equal_hashes_of_unequal_windows_are_told_apart():
    order = np.arange(3)
    text = b" ".join([b"a"] * 13) + b"\n" + b" ".join([b"b"] * 13) + b"\n" + b" ".join([b"a"] * 13)
    starts = np.arange(0, len(text), 2)
    group = substrings._told_apart(text, order, np.zeros(3, int), np.array([0]), np.array([0, 13, 26]), starts, starts + 1)
    assert group.tolist() == [0, 1, 0]
