"""The corpus pipeline: five stages over ``documents``, each on all that the one before kept.

Every stage takes (spark, docs, sf_dir).  Its result is written as Parquet and read again
as the next one's input.  The last adds how many words the mix takes of each document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossgrid.llm import decontaminate, exact, language, minhash, mixing
from lossgrid.llm.store import Scratch, keyed, without

#: Labelled documents score 0.38 and more in their own language, random letters and languages that
#: were not learned 0.18 to 0.25: below this a text is in none of the languages.
LEAST_SCORE = 0.3


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without letters and texts unlike every learned language go."""
    return language.keep_identified(docs, LEAST_SCORE)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of texts that are equal but for white space the longest stays, then the smallest doc_id."""
    return exact.keep_first(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by a share of 0.8 of five-word shingles stays."""
    docs, key, _ = keyed(docs, Scratch(spark, "near-keys"))
    found = minhash.near_duplicates(docs.select(F.col(key).alias("doc_id"), "text"), shingle=5, percent=80)
    return without(docs, found.where("not kept").select(F.col("doc_id").alias(key)), key)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with ten consecutive words of a benchmark item go."""
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    docs, key, _ = keyed(docs, Scratch(spark, "leak-keys"))
    found = decontaminate.contamination(docs.select(F.col(key).alias("doc_id"), "text"), items, length=10)
    return without(docs, found.where("contaminated").select(F.col("doc_id").alias(key)), key)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target and taken of every remaining document."""
    return mixing.mix(docs)


STAGES = [
    ("language identification", identify_language),
    ("exact dedup", drop_exact_copies),
    ("near dedup", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("mixing to weights", mix_sources),
]

#: Language profiles and the mix cannot be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table documents."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = scratch.save(stage(spark, docs, sf_dir), f"stage-{k}")
        if k > 1:
            scratch.drop(f"stage-{k - 2}")
    return docs
