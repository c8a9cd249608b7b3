"""The given tables, and SQL over them without session-wide views."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sql(spark: SparkSession, sf_dir: str, text: str, **more: DataFrame) -> DataFrame:
    """Run SQL whose tables stand in braces, as {part}; others may be passed by name."""
    used = {n: table(spark, sf_dir, n) for n in set(re.findall(r"\{(\w+)\}", text)) - set(more)}
    return spark.sql(text, **used, **more)


def plain(text: str) -> str:
    """The same SQL for an engine where the tables are views."""
    return re.sub(r"\{(\w+)\}", r"\1", text)
