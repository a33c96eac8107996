"""The corpus pipeline: quality, line dedup, near-dedup, decontamination, tokens.

Each stage is a function of (spark, docs, sf_dir) that works on all rows its predecessor kept and
returns a DataFrame; all but the last return the columns of their input. ``run`` writes each
stage's result to the shared folder and reads it again, so a lost executor repeats one stage at
most. Null and empty texts pass every stage but the first, which scores them like any other text;
very long texts pass whole. Repeated rows are treated alike in every stage; near-duplicates that tie
leave the least id. Rows travel in structs, so extra columns may have any name; empty tables give
empty tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linetensor.llm import bpe, decontaminate, lines, neardup, quality
from linetensor.llm.common import table, written
from linetensor.llm.langid import held_out
from linetensor.llm.registry import tokenizer_path


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble accepts; it is learned from the labels that are not held out."""
    labels = table(spark, sf_dir, "labels", "doc_id", "quality").where(~held_out("doc_id", 3, 1))
    return quality.accepted(docs, quality.learn(docs, labels))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without later occurrences of three lines; n_chars follows the text."""
    done = lines.dedup_lines(docs)
    new = {"text": F.col("kept_text"), "n_chars": F.length("kept_text").cast("long")}
    return done.select(*[new.get(c, F.col(f"row.`{c}`")).alias(c) for c in docs.columns])


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class."""
    return neardup.without_near_duplicates(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of what is left."""
    return bpe.round_trip_digest(docs, tokenizer_path("word_bpe_49k.json"))


STAGES = [("quality", quality_filter), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("decontamination", decontamination), ("tokens", tokens)]

#: SQL cannot express the learned rules, the sampled bands or the merges; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
