"""A corpus pipeline of five stages, each a function of (spark, docs, sf_dir).

Every stage but the last returns the columns of documents. Null and empty texts have no language and go
in the first stage; an empty table stays empty in all. A stage's models are learned from its own input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotrank.llm.decontaminate import leaks
from pivotrank.llm.language import fit
from pivotrank.llm.near_dup import classes
from pivotrank.llm.registry import sentence_pieces
from pivotrank.llm.session import table
from pivotrank.llm.substring_dedup import remove_repeats

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the model can tell; ``lang`` stays as given."""
    return docs.select(*COLUMNS).where(fit(docs).identified("text"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class: that of the smallest doc_id. Rows without a doc_id stay, as do rows that repeat one."""
    others = classes(docs).where(F.col("doc_id") != F.col("class_id")).select("doc_id")
    return docs.join(others, "doc_id", "left_anti").select(*COLUMNS)


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages that an earlier one has; texts that lose none stay as they are."""
    out = remove_repeats(docs, carry=True)
    text = F.when(F.col("n_removed") > 0, F.col("kept")).otherwise(F.col("text"))
    return out.select("doc_id", text.alias("text"), "rest.lang", "rest.source", F.when(F.col("n_removed") > 0, F.char_length(text).cast("long")).otherwise(F.col("rest.n_chars")).alias("n_chars"))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark passage."""
    return leaks(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark")).where(F.size("leaks") == 0).select(*COLUMNS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id and the ids of its text, with the checks of the encoder."""
    return sentence_pieces().encode_documents(docs.select("doc_id", "text")).select("doc_id", F.size("ids").alias("n_tokens"), "ids", "parity", "round_trip")


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("substrings", substrings),
    ("decontamination", decontamination),
    ("tokens", tokens),
]

ORACLE_SQL = None  # learned models and a tokenizer have no SQL; tests compare the stages with brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages' result over the documents of a folder."""
    docs = table(spark, sf_dir, "documents").select(*COLUMNS)
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs
