"""Corpus pipeline: quality rules, toxicity, near duplicates, repeated strings, packing.

Each stage takes ``(spark, docs, sf_dir)`` and works on all rows its predecessor kept.
All but the last return the columns of ``documents``; the last returns packed pieces.

Every stage passes any columns on, whatever their names, and gives an empty table for an
empty one. Null and blank texts fail the quality rules and go there; in the later stages alone
they count as empty: not toxic, similar to nothing, one piece holding the end id. Rows that repeat
an id and a text are one document to the Jaccard stage, which keeps one of them; rows that
repeat an id with another text are documents of their own throughout. Ties go to the smallest id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulecredit.llm import jaccard_join, packing, quality, suffix_dedup, toxicity
from rulecredit.llm.runtime import SharedStore


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.kept_documents(docs)


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.clean_documents(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.one_per_component(docs)


#: Passages of over 50 words that repeat go: so many words, in at least so many bytes (natural
#: text of 51 words has more); repeated strings of ``suffix_dedup.MIN_BYTES`` go however few words they hold.
PASSAGE_BYTES, PASSAGE_WORDS = 200, 51


def repeated_string_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = suffix_dedup.remove_repeats(docs, PASSAGE_BYTES, PASSAGE_WORDS)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("quality_rules", quality_stage),
    ("toxicity", toxicity_stage),
    ("ngram_jaccard_join", near_duplicate_stage),
    ("suffix_array_dedup", repeated_string_stage),
    ("best_fit_packing", packing_stage),
]

#: BPE ids, learned lexicons and components have no SQL form; tests hold the result against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = SharedStore(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = store.write(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
