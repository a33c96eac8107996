"""Chat formatting by prefix-target expansion.

Every assistant turn becomes an example of its own: all turns before it as context, and only its
own text trainable, given as the stretch of the formatted string under the loss mask. Turns after
the last assistant turn (or all, where there is none) come as a last example that trains nothing,
so that the examples hold the whole conversation.

A turn is written as ``<|turn|>`` role ``<|text|>`` text ``<|end|>``. Control strings inside roles
and texts are broken by a backslash after their first character, and backslashes are doubled, so
nothing in a text reads as a mark and all of it can be read back.

Cases: turns follow (turn, role, text), nulls first, so ties have one order and repeated rows stay.
Null roles and texts read as the empty string; a null conv_id is a conversation too. Extra columns
are left alone; an empty table has no examples. A conversation is streamed through one task in
order of its turns: its context grows with it, as the method wants, and nothing else is kept.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, rows_out

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>"
#: Control strings of common chat templates, which texts must not pass for.
CONTROL = ("<|", "[INST]", "[/INST]", "<s>", "</s>", "<<SYS>>", "<</SYS>>")
ASSISTANT = "assistant"
_CONTROL = re.compile("|".join(re.escape(c[0]) + f"(?={re.escape(c[1:])})" for c in CONTROL))
_ESCAPED = re.compile(r"\\(\\?)")
_WRITTEN = re.compile(rf"{re.escape(TURN)}(.*?){re.escape(TEXT)}(.*?){re.escape(END)}", re.DOTALL)


def escape(text: str) -> str:
    return _CONTROL.sub(lambda m: m.group() + "\\", text.replace("\\", "\\\\"))


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text) if "\\" in text else text


def parse(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a formatted string."""
    return [(unescape(role), unescape(text)) for role, text in _WRITTEN.findall(formatted)]


def expand_examples(df: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """One row per example, those of a conversation in order and together: conv, example, n_turns, formatted, loss_start, loss_end.

    Offsets are code points; an example that trains nothing has an empty stretch at its end.
    """
    rows = df.select(F.col(conv).alias("conv"), F.col(turn).alias("turn"), F.col(role).alias("role"), F.col(text).alias("text"))
    rows = rows.repartition("conv").sortWithinPartitions("conv", "turn", "role", "text")
    fields = [("example", pa.int64()), ("n_turns", pa.int64()), ("formatted", pa.string()), ("loss_start", pa.int64()), ("loss_end", pa.int64())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = pa.schema([("conv", pa.int64()), *fields])

        def examples():
            nothing = object()
            held, context, example, turns, open_turns = nothing, "", 0, 0, False
            for batch in batches:
                for c, _, r, t in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                    if c != held or held is nothing:
                        if open_turns:
                            yield held, example, turns, context, len(context), len(context)
                        held, context, example, turns = c, "", 0, 0
                    context += f"{TURN}{escape(r or '')}{TEXT}"
                    start = len(context)
                    context += escape(t or "")
                    end = len(context)
                    context += END
                    turns += 1
                    open_turns = r != ASSISTANT
                    if not open_turns:
                        yield held, example, turns, context, start, end
                        example += 1
            if open_turns:
                yield held, example, turns, context, len(context), len(context)

        yield from rows_out(examples(), out, weigh=lambda row: len(row[3]))

    return arrow_map(rows.withColumn("conv", F.col("conv").cast("long")), run, "conv long, example long, n_turns long, formatted string, loss_start long, loss_end long").withColumnRenamed("conv", conv)


def read_back(examples: DataFrame, conv: str = "conv_id") -> DataFrame:
    """Per conversation, from its examples, which stand together: turns, loss texts and lengths as read from the formatted strings."""
    rows = examples.select(F.col(conv).alias("conv"), "example", "formatted", "loss_start", "loss_end")
    fields = [("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64()), ("n_examples", pa.int64())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def close(held, last, loss, chars, total, n):
            turns = parse(last)
            digest = hashlib.sha256()
            for r, t in turns:
                digest.update(f"{r}\n{t}\n".encode("utf-8", "replace"))
            return held, len(turns), digest.hexdigest(), chars, loss.hexdigest(), total, n

        def digests():
            held, last, loss, chars, total, n = None, "", None, 0, 0, 0
            for batch in batches:
                for c, example, formatted, start, end in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                    if example == 0:
                        if loss is not None:
                            yield close(held, last, loss, chars, total, n)
                        held, loss, chars, total, n = c, hashlib.sha256(), 0, 0, 0
                    target = unescape(formatted[start:end])
                    loss.update(target.encode("utf-8", "replace"))
                    last, chars, total, n = formatted, chars + len(target), total + len(formatted), n + 1
            if loss is not None:
                yield close(held, last, loss, chars, total, n)

        yield from rows_out(digests(), pa.schema([("conv", pa.int64()), *fields]))

    return arrow_map(rows, run, "conv long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_examples long").withColumnRenamed("conv", conv)


#: The same figures by their definition.
DIGEST_SQL = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), sized AS (
  SELECT *, 23 + length(replace(replace(replace(replace(replace(replace(replace(replace(role, '\', '\\'),
      '<|', '<\|'), '[INST]', '[\INST]'), '[/INST]', '[\/INST]'), '<s>', '<\s>'), '</s>', '<\/s>'), '<<SYS>>', '<\<SYS>>'), '<</SYS>>', '<\</SYS>>'))
    + length(replace(replace(replace(replace(replace(replace(replace(replace(text, '\', '\\'),
      '<|', '<\|'), '[INST]', '[\INST]'), '[/INST]', '[\/INST]'), '<s>', '<\s>'), '</s>', '<\/s>'), '<<SYS>>', '<\<SYS>>'), '<</SYS>>', '<\</SYS>>')) AS size,
    row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC NULLS LAST, role DESC, text DESC) AS from_end
  FROM rows
), summed AS (
  SELECT *, sum(size) OVER (PARTITION BY conv_id ORDER BY from_end DESC) AS upto FROM sized
)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY from_end DESC)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY from_end DESC) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(upto) FILTER (role = 'assistant' OR from_end = 1)::BIGINT AS formatted_chars,
  count(*) FILTER (role = 'assistant' OR from_end = 1)::BIGINT AS n_examples
FROM summed GROUP BY conv_id
"""
