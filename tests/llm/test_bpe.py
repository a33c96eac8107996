import hashlib
import random

import public_tokenizers
import pytest
from tokenizers import Tokenizer

from linetensor.llm import bpe

PATH = public_tokenizers.path("word_bpe_49k.json")
TEXTS = [
    "", " \n\t", "Hello, World! it's 2024", "A<|endoftext|>b'S it's<|startoftext|> ΑΣ ΣΑΣ İ 中文字 123 🙂🙂 é",
    "a" * 700, "don't we'll I'VE " * 3, "éàü Straße ñandú naïve café", "x\u001cy\u0085z w", "ȺȾ Ᲊ ՘",
]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def test_ids_match_the_library(library):
    own = bpe.PrefixTrieEncoder(PATH)
    rng = random.Random(5)
    syllables = ["th", "er", "é", "ion", "ß", "qu", "1", "'", "##", "ing", "ó"]
    texts = TEXTS + [" ".join("".join(rng.choices(syllables, k=rng.randint(1, 9))) for _ in range(40)) for _ in range(100)]
    assert own.encode_texts(texts) == [e.ids for e in library.encode_batch(texts, add_special_tokens=False)]


def test_every_single_word_token_encodes_as_itself():
    own = bpe.PrefixTrieEncoder(PATH)
    for token, (left, right) in list(own.parts.items())[::37]:
        rank = own.rank.pop((left, right))
        assert own.stay_apart(left, right), token
        own.apart.clear()
        own.rank[left, right] = rank


def test_query_digests(spark, library):
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate([*TEXTS, None])], "doc_id long, text string, key string")
    rows = {r.doc_id: r for r in bpe.round_trip_digest(df, PATH).collect()}
    for i, text in enumerate([*TEXTS, None]):
        ids = library.encode(text or "", add_special_tokens=False).ids
        assert rows[i].n_tokens == len(ids)
        assert rows[i].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert rows[i].decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert bpe.round_trip_digest(df.limit(0), PATH).count() == 0
