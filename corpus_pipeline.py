"""A training corpus from raw documents: five stages, each over all rows its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.llm import contamination, langid, line_dedup, ngram_join, packing
from textfactor.llm.common import Scratch, table

#: Compression against trained dictionaries has no SQL form.
ORACLE_SQL = None


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter or with no language in front go; the others stay as they are."""
    known = langid.train(docs.where(langid.in_training()).select("doc_id", "text", "lang"))
    return langid.classify(docs, known).where("accepted").select(docs.columns)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document holds go; documents that lose every line go with them; n_chars follows the text."""
    kept = line_dedup.dedup_lines(docs).where("n_dropped = 0 or n_dropped < n_lines")
    return kept.withColumn("n_chars", F.length("text").cast("long")).select(docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near duplicates stays."""
    found, _ = ngram_join.near_duplicates(docs, whole_links=False)
    copies = found.where("component_id <> doc_id").select("doc_id").distinct()
    return docs.join(copies, "doc_id", "left_anti").select(docs.columns)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return contamination.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Boundary records of the packed token stream."""
    return packing.pack(docs, packing.default_tokenizer()).drop("piece_ids")


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", drop_repeated_lines),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark_leaks),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch, docs = Scratch(spark, "pipeline"), table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        mark = len(Scratch.made)
        docs = scratch.write(stage(spark, docs, sf_dir), name)
        Scratch.close_since(mark)  # the stage's result is written: what it was made from can go
    return docs
