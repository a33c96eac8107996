import hashlib
from collections import defaultdict

from harness import ROOT
from test_decontaminate import brute
from test_neardup import brute_classes
from tokenizers import Tokenizer

import corpus_pipeline
from linetensor.llm import lines, quality
from linetensor.llm.registry import tokenizer_path

SF = f"{ROOT}/sf0.001"


def by_line_windows(docs):
    """Texts after the removal of later three-line windows, by definition."""
    seen, places = set(), defaultdict(set)
    for k, t in docs:
        solid = [i for i, line in enumerate(t.split("\n")) if line.strip(lines.BLANKS)]
        for i in range(len(solid) - 2):
            content = tuple(t.split("\n")[j] for j in solid[i : i + 3])
            if content in seen:
                places[k].update(solid[i : i + 3])
            seen.add(content)
    return [(k, "\n".join(line for i, line in enumerate(t.split("\n")) if i not in places[k])) for k, t in docs]


def test_pipeline_matches_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = corpus_pipeline.quality_filter(spark, docs, SF)
    assert kept.columns == docs.columns
    model = quality.learn(docs, spark.read.parquet(f"{SF}/labels.parquet").where(~corpus_pipeline.held_out("doc_id", 3, 1)))
    import numpy as np

    stats = quality.statistics(docs).orderBy("doc_id").select("doc_id", "text", "stats").collect()
    scores = model.score(np.array([tuple(r.stats) for r in stats]))
    rows = [(r.doc_id, r.text) for r, s in zip(stats, scores, strict=True) if s >= 0.5]
    assert sorted(r.doc_id for r in kept.collect()) == [k for k, _ in rows]
    rows = by_line_windows(rows)
    classes = brute_classes(rows)
    rows = [(k, t) for k, t in rows if classes[k] == k]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    held = {k for k, _ in brute(rows, items)}
    rows = [(k, t) for k, t in rows if k not in held]
    library = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    wanted = {k: hashlib.sha256(" ".join(map(str, library.encode(t, add_special_tokens=False).ids)).encode()).hexdigest() for k, t in rows}
    assert {r.doc_id: r.ids_sha256 for r in corpus_pipeline.run(spark, SF).collect()} == wanted


def test_stages_handle_nulls_and_extra_columns(spark):
    rows = [(1, None, "en", None, 0, 1), (None, "some text\nhere", None, "s", 14, 2), (3, "", "en", "s", 0, 3), (3, "", "en", "s", 0, 4), (4, "x " * 5000, "fr", "s", 10000, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row int")
    for n, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, SF)
        assert stage(spark, docs.limit(0), SF).count() == 0, name
        if n < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns
        if n in (1, 2, 3):
            assert out.count() == len(rows), name
