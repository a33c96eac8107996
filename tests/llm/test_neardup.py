import math
import random
from collections import Counter, defaultdict

import numpy as np
from harness import ROOT

from linetensor.llm import neardup as n
from linetensor.llm.decontaminate import WORD
from linetensor.llm.registry import QUERIES


def brute_classes(docs):
    """Classes by comparing all pairs that share a shingle; shingles are words, and frequencies are counted exactly."""
    sets = {}
    for k, t in docs:
        words = WORD.findall((t or "").lower())
        if words:
            sets[k] = Counter(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4)))
    frequency = Counter(x for s in sets.values() for x in s)
    floor = max(1.0, len(sets) / 1024)
    factor = {x: 0.5 + 0.5 * math.log(len(sets) / c) / math.log(len(sets) / floor) if c > floor else 1.0 for x, c in frequency.items()}
    weighted = {k: {x: c * factor[x] for x, c in s.items()} for k, s in sets.items()}
    whole = {k: sum(s.values()) for k, s in weighted.items()}
    parent = {k: k for k, _ in docs}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    held = defaultdict(list)
    for k, s in weighted.items():
        common = Counter()
        for x, w in s.items():
            for j in held[x]:
                common[j] += min(w, weighted[j][x])
            held[x].append(k)
        for j, c in common.items():
            if c >= n.LEAST * (whole[j] + whole[k] - c):
                a, b = sorted((find(j), find(k)))
                parent[b] = a
    return {k: find(k) for k in parent}


def test_query_matches_brute_force(spark):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{ROOT}/sf0.01/documents.parquet").orderBy("doc_id").collect()]
    rows = QUERIES["op7_near_dedup"](spark, f"{ROOT}/sf0.01").collect()
    assert len(rows) == len(docs)
    assert {r.doc_id: r.class_id for r in rows} == brute_classes(docs)


def test_agreement_follows_similarity():
    rng = np.random.default_rng(5)
    idf = n.Idf(np.zeros(0, np.uint64), np.zeros(0, np.float32))
    agree, wanted = [], []
    for _ in range(60):
        common, own = rng.integers(20, 200), rng.integers(1, 60)
        a = np.unique(rng.integers(0, 2**63, common + own).astype(np.uint64))
        b = np.unique(np.concatenate([a[: len(a) - own], rng.integers(0, 2**63, own).astype(np.uint64)]))
        wa, wb = n.weights(a, rng.integers(1, 4, len(a)), idf), n.weights(b, rng.integers(1, 4, len(b)), idf)
        one, two = n.samples(np.concatenate([a, b]), np.concatenate([wa, wb]), np.array([0, len(a)]))
        agree.append((one == two).mean())
        wanted.append(n.similarity((a, wa), (b, wb)))
    assert abs(np.mean(agree) - np.mean(wanted)) < 0.03
    assert np.corrcoef(agree, wanted)[0, 1] > 0.8  # few samples a pair


def test_groups_and_cases(spark):
    rng = random.Random(3)
    base = [f"w{i}" for i in range(120)]
    hot = [f"h{i}" for i in range(60)]
    rows = []
    for i in range(150):  # near copies that differ in one word each
        words = list(base)
        words[rng.randrange(120)] = f"x{i}"
        rows.append((i, " ".join(words)))
    rows += [(200 + i, " ".join(base)) for i in range(40)]
    rows += [(300 + i, " ".join(hot + [f"y{i}-{j}" for j in range(60)])) for i in range(60)]  # a shared passage alone
    rows += [(400, None), (401, ""), (402, "one two"), (403, "One, two!"), (None, "one two"), (404, "?!"), (405, "one two"), (405, "one two")]
    df = spark.createDataFrame([(k, t, 1) for k, t in rows], "doc_id long, text string, class long")
    out = n.near_duplicates(df)
    got = {r.doc_id: r.class_id for r in out.collect()}
    assert out.count() == len(rows)
    assert {got[i] for i in range(150)} == {0} and {got[200 + i] for i in range(40)} == {0}
    assert all(got[300 + i] == 300 + i for i in range(60))
    assert [got[k] for k in (400, 401, 402, 403, None, 404, 405)] == [400, 401, 402, 402, None, 404, 402]
    left = n.without_near_duplicates(df)
    assert left.columns == df.columns
    assert sorted(r.doc_id for r in left.collect() if r.doc_id is not None) == [0, *range(300, 360), 400, 401, 402, 404]
    assert n.near_duplicates(df.limit(0)).count() == 0


def test_true_pairs_among_boilerplate_match_brute_force(spark):
    rng = random.Random(11)
    hot = [f"h{i}" for i in range(164)]
    rows = []
    for i in range(260):  # similarity 0.6 to each other
        own = [f"y{i}x{j}" for j in range(26)]
        rows.append((2 * i, " ".join(hot + own)))
        if i < 80:  # a chain of three texts, each about 0.8 to 0.9 like the one before
            for k in (1, 2):
                cut = rng.randrange(9, 14)
                own = own[:-cut] + [f"z{i}x{k}x{j}" for j in range(cut)]
                rows.append((2 * i + 1 if k == 1 else 10_000 + i, " ".join(hot + own)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    wanted = brute_classes(rows)
    assert sum(c != k for k, c in wanted.items()) > 80  # the fixture holds true pairs
    assert {r.doc_id: r.class_id for r in n.near_duplicates(df).collect()} == wanted


def test_prefixes_of_similar_sets_meet():
    rng = np.random.default_rng(2)
    for _ in range(200):
        pool = np.unique(rng.integers(0, 2**63, 60).astype(np.uint64))
        factors = rng.choice([0.5, 0.7, 1.0], len(pool))
        sets = [(np.sort(i), rng.integers(1, 3, len(i))) for i in (np.flatnonzero(rng.random(len(pool)) < 0.93) for _ in range(2))]
        (a, wa), (b, wb) = [(pool[i], (t * factors[i]).astype(np.float32)) for i, t in sets]
        if n.similarity((a, wa), (b, wb)) >= n.LEAST:
            (one, rest, whole), (two, rest_2, whole_2) = [n.prefix(s, w, factors[i]) for (s, w), (i, _) in zip(((a, wa), (b, wb)), sets, strict=True)]
            met, i, j = np.intersect1d(one, two, return_indices=True)
            assert any(min(rest[x], rest_2[y]) * 1.8 >= 0.8 * (whole + whole_2) * (1 - n.SLACK) for x, y in zip(i, j, strict=True))


def test_frequencies_are_exact(spark):
    rng = random.Random(4)
    docs = [(i, " ".join(rng.choices(["a", "b", "c"], k=30)) + f" own{i}") for i in range(3000)]
    rows = spark.createDataFrame(docs, "key long, text string").repartition(7)
    idf = n._idf(n._count(rows), rows)
    frequency = Counter()
    for _, t in docs:
        frequency.update(n.weighted_set(n.word_hashes(t))[0].tolist())
    floor = 3000 / 1024
    wanted = {x: 0.5 + 0.5 * math.log(3000 / c) / math.log(1024) for x, c in frequency.items() if c > floor}
    assert dict(zip(idf.shingles.tolist(), idf.factors.tolist(), strict=True)).keys() == wanted.keys()
    assert np.allclose(idf.factors, [wanted[x] for x in idf.shingles.tolist()])
    assert (np.diff(idf.shingles.astype(object)) > 0).all() and len(wanted) > 200


def test_words_are_those_of_the_pattern():
    texts = ["", None, "a_b Ünï ΑΣ ΑΣ1 x\u00b2 İ 中文 𝔸b", "x" * (n.CHARACTERS + 5) + " y", "word " * (n.CHARACTERS // 2), "?!"]
    got = n.words_of_all(texts)
    by_word = {}
    for t, hashes in zip(texts, got, strict=True):
        words = WORD.findall((t or "").lower())
        assert len(words) == len(hashes)
        for w, h in zip(words, hashes.tolist(), strict=True):
            assert by_word.setdefault(w, h) == h
    assert len(set(by_word.values())) == len(by_word)


def test_several_clusters_in_large_groups_match_brute_force(spark):
    """Boilerplate that all share, clusters of near copies of any size that no pivot needs to hit, and chains."""
    rng = random.Random(8)
    hot = [f"h{i}" for i in range(150)]
    rows, at = [], 0
    for c in range(12):
        base = [f"c{c}x{j}" for j in range(60)]
        for _ in range([2, 3, 14, 40][c % 4]):
            words = hot + base
            for _ in range(rng.randrange(0, 4)):
                words[rng.randrange(len(words))] = f"e{at}x{rng.randrange(9)}"
            rows.append((at, " ".join(words)))
            at += 1
    rows += [(at + i, " ".join(hot + [f"s{i}x{j}" for j in range(60)])) for i in range(120)]
    rng.shuffle(rows)
    wanted = brute_classes(rows)
    assert {r.doc_id: r.class_id for r in n.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()} == wanted
    assert len(set(wanted.values())) > 100


def test_small_cells_and_samples_match_brute_force(spark, monkeypatch):
    for name, value in (("TOGETHER", 4), ("PIVOTS", 1), ("PARTNERS", 3), ("PAYS", 1000)):
        monkeypatch.setattr(n, name, value)
    test_several_clusters_in_large_groups_match_brute_force(spark)


def test_texts_of_members_travel_compressed(spark):
    """They are shuffled for each candidate pair: packed they take less than half, and come back as they were."""
    given = {k: f"naïve {k} ☃ " + "the same few words once more, " * 40 for k in range(5)} | {5: ""}
    rows = spark.createDataFrame(list(given.items()), "key long, text string")
    held = n._members(rows.select("key").where("key <> 1"), rows).toArrow()
    texts = dict(zip(held["key"].to_pylist(), n._unpacked(held["text"]), strict=True))
    assert texts == {k: t for k, t in given.items() if k != 1}
    assert sum(map(len, held["text"].to_pylist())) * 2 < sum(len(t.encode()) for t in texts.values())
