"""A corpus pipeline of five of the training-data operators; each stage works on what the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.llm import chosen_path, cross_parsing, dominance_packing, edit_join, suffix_decontam
from factorclust.llm.queries import table, tokenizer
from factorclust.llm.shared import bounded_batches, cut, free_name


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter go, and those that the parse finds to be of no learned language."""
    bounded_batches(spark)
    return cross_parsing.keep_identified(docs)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of lines at most one, two or three edits apart, by their length, the first one stays; documents that have no line left go."""
    bounded_batches(spark)
    n_lines, n_removed = free_name(docs.columns, "n_lines"), free_name(docs.columns, "n_removed")
    found = edit_join.dedup(docs, edit_join.GROWN, blank=edit_join.WHITE, counts=(n_lines, n_removed))
    changed = F.col(n_removed) > 0
    empty = changed & (F.btrim("text", F.lit(edit_join.WHITE + "\n")) == "")
    length = F.when(changed, F.char_length("text").cast("long")).otherwise(F.col("n_chars")).alias("n_chars")
    return found.where(~F.coalesce(empty, F.lit(False))).select(*[length if c == "n_chars" else F.col(f"`{c}`") for c in docs.columns])


def keep_one_of_a_class(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of the documents that share four fifths of their word 5-grams the one with the least doc_id stays."""
    bounded_batches(spark)
    return chosen_path.keep_first(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which a twentieth lies in windows of a benchmark item go."""
    return suffix_decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of what is left, in sequences of 2048 tokens."""
    bounded_batches(spark)
    return dominance_packing.pack(docs, tokenizer())


STAGES = [
    ("language", identify_language),
    ("lines", dedup_lines),
    ("near_duplicates", keep_one_of_a_class),
    ("decontamination", decontaminate),
    ("packing", pack),
]

#: SQL can't express the tokenizer nor the language model; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
