import numpy as np
from harness import ROOT

from linetensor.llm import quality
from linetensor.llm.registry import QUERIES


def test_rules_are_found_and_sparse():
    rng = np.random.default_rng(0)
    x = rng.random((2000, len(quality.NAMES)))
    y = ((x[:, 2] > 0.5) & (x[:, 4] <= 0.7)).astype(int)
    model = quality.fit_rules(x, y)
    assert ((model.score(x) >= 0.5) == y).mean() > 0.97
    assert 0 < len(model.rules) < 120
    assert all(0 < len(conditions) <= quality.DEPTH for conditions, _ in model.rules)


def test_held_out_accuracy(spark):
    labels = spark.read.parquet(f"{ROOT}/sf0.1/labels.parquet")
    rows = QUERIES["op6_quality_rules"](spark, f"{ROOT}/sf0.1").join(labels, "doc_id").where("held_out").collect()
    right = sum(r.predicted == r.quality for r in rows) / len(rows)
    print("held-out accuracy", right, "rejected clean", sum(r.predicted < r.quality for r in rows), "kept bad", sum(r.predicted > r.quality for r in rows), len(rows))
    assert right > 0.95


def test_column_equals_numpy_and_cases(spark):
    rows = [(1, "Word word WORD. " * 30, 7), (2, None, 7), (3, "", 7), (4, "a### b&&& c***", 7), (5, "| x | y |\n" * 900, 7), (None, "plain text here", 7), (6, "dup", 7), (6, "dup", 7)]
    df = spark.createDataFrame(rows, "doc_id long, text string, stats int")
    labels = spark.createDataFrame([(1, 1), (4, 0), (1, 0), (None, 1), (6, 1), (9, 1)], "doc_id long, quality int")
    model = quality.RuleEnsemble(0.3, [(((0, True, 5.0), (1, False, 40.0)), -1.5), (((3, True, 0.5),), 0.7)])
    with_stats = quality.statistics(df.drop("stats"))
    x = np.array([tuple(r.stats) for r in with_stats.collect()])
    got = [r.s for r in with_stats.select(model.column().alias("s")).collect()]
    assert np.allclose(got, model.score(x))
    done = quality.classify(df, labels).collect()
    assert len(done) == len(rows) and all(0 <= r.score <= 1 for r in done)
    assert {r.score for r in quality.classify(df, labels.limit(0)).collect()} == {0.5}
    assert quality.classify(df.limit(0), labels).count() == 0


def test_columns_of_any_name_are_left_alone(spark):
    rows = [(1, "some text here", 7, 8, 9, "a"), (2, None, 1, 2, 3, "b"), (2, "word " * 60_000, 1, 2, 3, "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, stats int, quality_score int, __text int, label string")
    done = quality.score_rows(df, quality.RuleEnsemble(0.5)).orderBy("row.label")
    assert [tuple(r.row) for r in done.collect()] == rows
    assert quality.score_documents(df, quality.RuleEnsemble(0.5)).columns == ["doc_id", "text", "stats", "__text", "label", "quality_score", "quality_predicted"]


def test_accepted_keeps_the_rows_predicted_1(spark):
    """Same rows as by the prediction, repeats and clashing names included; texts are split once in the plan."""
    rule = (((quality.NAMES.index("words"), True, 2.5), (quality.NAMES.index("distinct_share"), True, 0.5)), 4.0)
    model = quality.RuleEnsemble(-2.0, [rule, (((quality.NAMES.index("words"), False, 9.5),), 0.5)])
    rows = [(1, "a b c d", "x"), (1, "a b c d", "x"), (2, "a a a a a", "y"), (3, None, "z"), (4, "", None), (None, "one two three " * 50, "w"), (5, "word " * 10 + "p q r s t u v w x y z", "v")]
    df = spark.createDataFrame(rows, "doc_id long, text string, stats string").selectExpr("*", "stats AS score", "1 AS row", "2 AS predicted", "3 AS __text")
    kept = quality.accepted(df, model)
    assert kept.columns == df.columns
    want = [tuple(r["row"]) for r in quality.score_rows(df, model).collect() if r["predicted"] == 1]
    assert sorted(map(repr, map(tuple, kept.collect()))) == sorted(map(repr, want)) and len(want) == 3
    assert kept._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1
    assert quality.accepted(df.limit(0), model).count() == 0
