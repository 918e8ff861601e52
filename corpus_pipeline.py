"""A corpus pipeline of five stages; each reads what the one before it kept, and its decisions take effect.

quality rules -> near duplicates (5-word shingles, Jaccard 0.8) -> benchmark decontamination -> mixing to target weights -> token files.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sketchfit.llm import decontaminate, mixing, near_duplicates, quality_rules, token_files

#: Target shares of tokens by domain; the domain with the largest share never loses tokens.
TARGETS = {"good": 0.9, "poor": 0.09, "toxic": 0.01}


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep_good(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_duplicates.drop_near_duplicates(docs, n=5, num=80, den=100)


def benchmark_free(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    labels = mixing.label_domains(spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return mixing.mix(docs, labels, TARGETS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return token_files.token_rows(spark, docs)


STAGES = [
    ("quality_rules", quality),
    ("ngram_jaccard", near_copies),
    ("decontaminate", benchmark_free),
    ("mixing", mixed),
    ("token_files", tokens),
]

#: SQL cannot express zstandard ratios, the classifier or the tokenizer; tests/llm holds the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in turn, each written as Parquet and read again."""
    from sketchfit.llm.common import stored

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
