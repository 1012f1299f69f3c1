"""A training corpus from documents: quality, near duplicates, personal data, mixing, encoding.

Each stage takes (spark, docs, sf_dir) and works on all rows that the one before kept; its result is written as Parquet
and reread as the next one's docs. All but the last return the columns of documents, further ones included, whatever their
names. Null and empty texts score as the model's bias says, are near copies of nothing, hold no personal data, and have no
words, so the mixture takes none of them; repeated rows are near copies; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from purchase_planner.functions.shipping import ship
from purchase_planner.llm import bpe_lookup, curriculum, jaccard_regions, pii_disclosure, subword_quality
from purchase_planner.llm._shared import settle
from purchase_planner.llm.queries import tokenizer_path

KEEP_FROM = 0.3


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents whose score is below KEEP_FROM; the model learns from the labels that are not held out."""
    ship(spark)
    model = subword_quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), ~subword_quality.held_out())
    return subword_quality.accepted(docs, model, KEEP_FROM)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of smallest id of each group linked by five-word shingles at 0.8 or more."""
    ship(spark)
    return jaccard_regions.deduplicated(docs, words=5, percent=80)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by its kind, and generalises or removes the terms that disclose it."""
    return pii_disclosure.sanitised(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats or cuts documents towards the sources' targets, in the order of training."""
    return curriculum.mixed(docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens and the ids of every text."""
    ship(spark)
    return bpe_lookup.encode(spark, docs, tokenizer_path(), carry=["lang", "source"]).select("doc_id", "lang", "source", F.size("ids").cast("long").alias("n_tokens"), "ids")


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("mixture", mixture), ("encoding", encoding)]

#: The stages learn a model, search near duplicates and rank terms; SQL cannot express them. Tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = settle(docs)
    return docs
