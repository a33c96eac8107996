from harness import ROOT, spark_rows, sql_rows

from linetensor.llm import lines
from linetensor.llm.registry import ORACLES, QUERIES


def test_query_matches_sql(spark):
    name = "op10_line_dedup"
    assert spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.01")) == sql_rows(ORACLES[name], "sf0.01")


def test_cases(spark):
    rows = [
        (1, "a\nb\nc\nd", 0), (2, "x\na\nb\n\nc\nd\ny", 0), (3, None, 0), (4, "", 0), (5, "q\nq\nq\nq\nq", 0), (6, "a\nb", 0),
        (None, "a\nb\nc", 0), (7, "new\na\nb\nc", 1), (7, "a\nb\nc\nnew", 2), (8, "z\nz1\nz2", 1), (8, "z\nz1\nz2", 2),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_lines int")
    done = {(r.row.doc_id, r.row.n_lines): r for r in lines.dedup_lines(df).collect()}
    assert len(done) == len(rows)
    assert done[None, 0].kept_text == "a\nb\nc"
    assert done[1, 0].kept_text == "" and done[1, 0].n_removed == 4 or done[1, 0].kept_text == "d"
    assert done[2, 0].kept_text == "x\n\ny" and done[2, 0].n_removed == 4
    assert done[3, 0].kept_text is None and done[4, 0].kept_text == "" and done[6, 0].kept_text == "a\nb"
    assert done[5, 0].kept_text == "q" and done[5, 0].n_lines == 5
    assert done[7, 1].kept_text == "new" and done[7, 2].kept_text == "new"
    assert done[8, 1].kept_text == done[8, 2].kept_text == "z\nz1\nz2"
    assert lines.dedup_lines(df.limit(0)).count() == 0
