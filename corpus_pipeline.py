"""From documents to token records: quality rules, one of each near-duplicate group, no benchmark passages, mixed sources, binary records.

A stage's result is written before the next stage is called, as run() does: a stage deletes the tables that the one before left in
the shared folder, unless its docs read them still.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession

from recmatch.llm import contamination, jaccard, mixing, quality, records
from recmatch.llm.common import documents, noting, scratch, swept

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
#: Folders of tables that stages have left, by application.
_left: dict[str, list[str]] = {}


def tidy_stage(stage: Stage) -> Stage:
    @wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        left = _left.setdefault(spark.sparkContext.applicationId, [])
        swept(docs, left)
        with noting() as made:
            out = stage(spark, docs, sf_dir)
        left += made
        return out

    return run_stage


@tidy_stage
def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs)


@tidy_stage
def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard.one_of_each(docs, jaccard.Rule(words=5, percent=80))


@tidy_stage
def uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return contamination.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


@tidy_stage
def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.take(docs)


@tidy_stage
def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return records.digest(docs, scratch(spark, "records"))


STAGES = [
    ("quality rules", good),
    ("n-gram Jaccard join", distinct),
    ("benchmark decontamination", uncontaminated),
    ("mixing sources to target weights", mixed),
    ("token-ID / binary output", tokens),
]
#: SQL has neither the tokenizers nor the near-duplicate graph in reasonable time; tests/llm/test_pipeline.py compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    where = scratch(spark, "pipeline")
    for n, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{where}/{n}")
        docs = spark.read.parquet(f"{where}/{n}")
    return docs
