"""Corpus pipeline: quality, line dedup, near duplicates, mixing, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; all but the last return the
columns of `documents`. `run` writes every stage's rows into the shared folder before the next one reads them.

All stages take null, empty and very long texts, null ids, repeated rows and empty tables: quality keeps empty texts, lines
drops rows without words, near_duplicates keeps one of repeated rows, mixture counts them apart, sequences packs each of
them. An empty table gives empty results. Extra columns of any name go through all stages but the last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gamat.llm import jaccard_join, kneser_ney, line_templates, mixing, packing
from gamat.llm.common import cut


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose perplexity under the model of trusted text is in the usual range of their language."""
    return kneser_ney.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of recurring templates go; a document of which no word remains goes too. n_chars follows the text."""
    out = line_templates.dedup_lines(docs)
    out = out.where((F.col("__dropped") <= 0) | F.col("__text").rlike(r"[^ \t\n\x0B\f\r]"))
    changed = {"text": F.col("__text"), "n_chars": F.when(F.col("__dropped") > 0, F.length("__text").cast("long")).otherwise(F.col("__row.n_chars"))}
    return out.select(*[changed.get(c, F.col(f"__row.`{c}`")).alias(c) for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of linked documents stays."""
    return jaccard_join.keep_one(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Nine tenths of the tokens, by the target weights; no document twice."""
    return mixing.choose(docs, fraction=0.9, max_epochs=1)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their place in sequences of 4096 tokens."""
    return packing.pack(docs)


STAGES = [("quality", quality), ("lines", lines), ("near_duplicates", near_duplicates), ("mixture", mixture), ("sequences", sequences)]
#: The quality, mixing and packing stages have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
