"""From raw documents to packed sequences.

Each stage takes (spark, docs, sf_dir) and works on all documents that the one
before it kept; all but the last return the columns of ``docs``. The stages use
near-duplicates on five-word shingles at a similarity of 0.8.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.cluster import Written
from pagecast.llm import near_dedup, packing, quality_classifier, quality_rules, substring_dedup
from pagecast.llm.words import unused

#: Documents below this probability of being good are rejected.
LEAST_SCORE = 0.3


def classify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Reject what the attention-based quality classifier scores low."""
    model = quality_classifier.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    score = unused("_score", docs)
    scored = quality_classifier.with_scores(docs, model, score_col=score)
    return scored.where(F.col(score) >= LEAST_SCORE).select(*docs.columns)


def apply_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Reject what fails the base rules or lies beyond its group's fences."""
    return quality_rules.filtered(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the document with the smallest id of each near-duplicate group."""
    return near_dedup.keep_one(docs)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Remove every passage's later copies from the texts."""
    return substring_dedup.remove_repeats(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Tokenise and pack into sequences of at most 4096 ids."""
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("quality_classifier", classify),
    ("quality_rules", apply_rules),
    ("near_dedup", drop_near_duplicates),
    ("substring_dedup", drop_repeated_passages),
    ("packing", pack),
]

#: The classifier and the sketches cannot be written in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, held = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES:
        made = Written(stage(spark, docs, sf_dir), f"pipeline-{name}")
        if held is not None:
            held.drop()
        docs, held = made.df, made
    return docs
