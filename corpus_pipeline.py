"""Corpus pipeline: language ID, line dedup, SimHash near-dedup, benchmark decontamination, best-fit packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents. The line
stage writes the shortened text and keeps every row; n_chars follows the text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist.llm import decontaminate, language_id, line_dedup, packing, simhash_dedup
from graphdist.runtime import materialize


def known_language(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without a letter (or NULL)."""
    training = docs.filter(~F.coalesce(language_id.held_out(F.col("doc_id")), F.lit(False))).select("doc_id", "text", "lang")
    return language_id.keep_identified(docs, language_id.train(training))


def distinct_lines(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    short = line_dedup.dedup_lines(docs)
    return short.select(*[F.length("text").cast("long").alias("n_chars") if c == "n_chars" else F.col(f"`{c}`") for c in docs.columns])


def one_of_each_group(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash_dedup.keep_one_per_group(docs)


def clean_of_benchmarks(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.keep_clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packed(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("language_id", known_language),
    ("line_dedup", distinct_lines),
    ("simhash_dedup", one_of_each_group),
    ("decontamination", clean_of_benchmarks),
    ("packing", packed),
]

#: SQL expresses neither the learned stages nor the tokenizer; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
