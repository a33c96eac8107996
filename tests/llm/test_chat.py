import hashlib

from harness import ROOT, spark_rows, sql_rows
from hypothesis import given
from hypothesis import strategies as st

from linetensor.llm import chat
from linetensor.llm.registry import ORACLES, QUERIES


@given(st.text(st.sampled_from(list("\\<>|[]/INSTSYs turnend</s>")), max_size=60))
def test_escaping_is_reversible_and_hides_marks(text):
    written = chat.escape(text)
    assert chat.unescape(written) == text
    assert not any(mark in written for mark in chat.CONTROL)
    assert chat.parse(f"{chat.TURN}{written}{chat.TEXT}{written}{chat.END}") == [(text, text)]


def test_examples(spark):
    rows = [(1, 2, "assistant", "b<|end|>", 0), (1, 0, "system", None, 0), (1, 1, "user", "a", 0), (1, 3, "user", "last", 0), (2, 0, "user", "only", 0), (None, 0, "assistant", "x", 0), (None, 0, "assistant", "x", 0), (3, None, None, "", 0), (4, 0, "assistant", "y" * 50_000, 0)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, example int")
    examples = chat.expand_examples(df)
    by = {(e.conv_id, e.example): e for e in examples.collect()}
    assert set(by) == {(1, 0), (1, 1), (2, 0), (None, 0), (None, 1), (3, 0), (4, 0)}
    first = by[1, 0]
    assert chat.unescape(first.formatted[first.loss_start : first.loss_end]) == "b<|end|>"
    assert chat.parse(by[1, 1].formatted) == [("system", ""), ("user", "a"), ("assistant", "b<|end|>"), ("user", "last")]
    assert by[1, 1].loss_start == by[1, 1].loss_end == len(by[1, 1].formatted)
    back = {r.conv_id: r for r in chat.read_back(examples).collect()}
    assert back[None].n_turns == 2 and back[None].loss_chars == 2 and back[2].loss_chars == 0
    assert back[2].loss_sha256 == hashlib.sha256(b"").hexdigest()
    assert chat.read_back(chat.expand_examples(df.limit(0))).count() == 0


def test_query_matches_sql(spark):
    name = "op1_chat_expansion"
    assert spark_rows(QUERIES[name](spark, f"{ROOT}/sf0.01")) == sql_rows(ORACLES[name], "sf0.01")
