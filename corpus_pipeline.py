"""A training corpus in five stages, each over all that the one before has kept."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from bandstore.llm import decontaminate, language_id, mixing, near_dup, sharding
from bandstore.llm.common import fresh
from bandstore.sources.shared import shared_dir


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without a letter, which have no language, go; also where no row has a label to learn
    from, so that a model without languages does not reject everything."""
    model = language_id.train(docs)
    if not model.languages:
        return docs.where(language_id.has_letter(docs["text"]))
    pred, score = fresh(docs.columns, "lang_pred", "score")
    found = language_id.identify(docs, model, pred=pred, score=score)
    return found.where(found[pred] != language_id.UNDETERMINED).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: five-word shingles, similarity 0.8."""
    return near_dup.drop_near_duplicates(docs, width=5, percent=80)


def remove_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.remove_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeat_documents(docs)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(docs)


STAGES = [
    ("language_id", identify_language),
    ("near_dup", drop_near_duplicates),
    ("decontamination", remove_benchmark),
    ("mixing", mix),
    ("sharding", shard),
]

#: No single SQL statement expresses near-duplicate components or seeded shuffles; the stages
#: are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    root = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{root}/{name}")
        docs = spark.read.parquet(f"{root}/{name}")
    return docs
