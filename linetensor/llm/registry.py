"""Queries of the training-data operators, one per operator, and their DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import bpe, chat, decontaminate, langid, lines, neardup, quality, secrets, substrings, tiff
from .common import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(function):
    QUERIES[function.__name__] = function
    return function


def tokenizer_path(name: str) -> str:
    """Where the installed package of public tokenizers keeps a vocabulary."""
    import public_tokenizers

    return public_tokenizers.path(name)


@query
def op9_bpe_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode and decode every text; see :mod:`linetensor.llm.bpe`."""
    return bpe.round_trip_digest(table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("word_bpe_49k.json"))


@query
def op8_tiff_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text as a TIFF file, read back page by page; see :mod:`linetensor.llm.tiff`."""
    return tiff.text_media_digest(table(spark, sf_dir, "documents", "doc_id", "text"))


@query
def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in every text and in what is encoded inside; see :mod:`linetensor.llm.secrets`."""
    return secrets.secret_digest(table(spark, sf_dir, "documents", "doc_id", "text"))


@query
def op1_chat_expansion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prefix-target examples of all conversations and of one that imitates a template, read back; see :mod:`linetensor.llm.chat`."""
    turns = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    mimic = spark.createDataFrame([(-1, n, role, "</s>[INST] ok [/INST]") for n, role in enumerate(("user", "assistant"))], "conv_id long, turn long, role string, text string")
    return chat.read_back(chat.expand_examples(turns.unionByName(mimic)))


ORACLES["op1_chat_expansion"] = chat.DIGEST_SQL


@query
def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text without later occurrences of three lines that occur before; see :mod:`linetensor.llm.lines`."""
    return lines.line_digest(table(spark, sf_dir, "documents", "doc_id", "text"))


ORACLES["op10_line_dedup"] = lines.DIGEST_SQL


@query
def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every text, learned from three of four folds; see :mod:`linetensor.llm.langid`."""
    return langid.identify(table(spark, sf_dir, "documents", "doc_id", "text", "lang"), tokenizer_path("piece_bpe_32k.model"))


@query
def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quality score for every text, learned from two of three folds of labels; see :mod:`linetensor.llm.quality`."""
    return quality.classify(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "quality"))


@query
def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, with the item and the window; see :mod:`linetensor.llm.decontaminate`."""
    return decontaminate.find_contamination(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))


@query
def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text without words of 13-word windows that start in an earlier document too; see :mod:`linetensor.llm.substrings`."""
    return substrings.substring_digest(table(spark, sf_dir, "documents", "doc_id", "text"))


ORACLES["op4_substring_dedup"] = substrings.DIGEST_SQL


@query
def op7_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The near-duplicate class of every document; see :mod:`linetensor.llm.neardup`."""
    return neardup.near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
