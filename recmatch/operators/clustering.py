"""Consistency by graphs of scored pairs."""

from __future__ import annotations

import gc

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def similarity_edges(scores: DataFrame, threshold: float) -> DataFrame:
    return scores.filter(F.col("score") >= threshold).select(F.col("anchor_id").alias("src_id"), F.col("cand_id").alias("dst_id"), F.col("score").alias("weight"))


def connected_components(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """rid, cluster_id, the least id reachable. Each round merges every node into the first of itself and its neighbours, in the order of a hash.

    A group of near copies is then a node or a few, and the edges within are gone: later rounds and shuffles are small. Reliable checkpoints.
    """
    spark = edges.sparkSession
    first = lambda c: F.struct(F.xxhash64(c).alias("h"), F.col(c).alias("l"))
    left, up = edges.select(F.col("src_id").alias("u"), F.col("dst_id").alias("v")), None
    left = left.union(left.select("v", "u")).distinct().checkpoint()
    for _ in range(rounds):
        step = left.groupBy("u").agg(F.least(F.min(first("v")), F.min(first("u")))["l"].alias("l")).checkpoint()
        up = step if up is None else up.join(step.select(F.col("u").alias("l"), F.col("l").alias("m")), "l", "left").select("u", F.coalesce("m", "l").alias("l")).checkpoint()
        left = left.join(step, "u").select("v", F.col("l").alias("x")).distinct().join(step.withColumnRenamed("u", "v"), "v").select(F.col("x").alias("u"), F.col("l").alias("v")).filter("u <> v").distinct().checkpoint()
        gc.collect()
        spark.sparkContext._jvm.System.gc()  # Spark deletes the shuffles and checkpoints that nobody can read
        if left.isEmpty():
            return up.join(up.groupBy("l").agg(F.min("u").alias("cluster_id")), "l").select(F.col("u").alias("rid"), "cluster_id")
    raise RuntimeError("components did not settle")


def mutual_best(edges: DataFrame) -> DataFrame:
    """Edges that are the best of both their ends; ties go to the smaller ids."""
    s = Window.partitionBy("src_id").orderBy(F.desc("weight"), "dst_id")
    d = Window.partitionBy("dst_id").orderBy(F.desc("weight"), "src_id")
    return edges.withColumn("rs", F.row_number().over(s)).withColumn("rd", F.row_number().over(d)).filter("rs = 1 and rd = 1").drop("rs", "rd")


def greedy_matching(edges: DataFrame, rounds: int = 100) -> DataFrame:
    """Greedy one-to-one matching by falling weight: rounds of edges that come first at both ends are exactly what the sequential scan takes."""
    order = [F.desc("weight"), F.col("src_id"), F.col("dst_id")]
    left, taken = edges.checkpoint(), None
    for _ in range(rounds):
        s, d = Window.partitionBy("src_id").orderBy(*order), Window.partitionBy("dst_id").orderBy(*order)
        top = left.withColumn("rs", F.row_number().over(s)).withColumn("rd", F.row_number().over(d)).filter("rs = 1 and rd = 1").select("src_id", "dst_id", "weight").checkpoint()
        taken = top if taken is None else taken.union(top)
        left = left.join(top.select("src_id"), "src_id", "left_anti").join(top.select("dst_id"), "dst_id", "left_anti").select("src_id", "dst_id", "weight").checkpoint()
        if left.isEmpty():
            return taken
    raise RuntimeError("the matching did not settle")


def canonicalise(members: DataFrame, records: DataFrame, by: str) -> DataFrame:
    """cluster_id, canonical_id, members: the record with the largest value of a column stands for its cluster; ties to the smaller id."""
    return members.join(records, "rid").groupBy("cluster_id").agg(F.max_by("rid", F.struct(by, -F.col("rid"))).alias("canonical_id"), F.count(F.lit(1)).alias("members"))


def consistency_report(decisions: DataFrame) -> DataFrame:
    """Anchors with more than one accepted candidate, candidates claimed by more than one anchor."""
    a = decisions.groupBy("anchor_id").count().agg(F.count_if(F.col("count") > 1).alias("anchors_with_many"), F.count(F.lit(1)).alias("anchors"))
    c = decisions.groupBy("cand_id").count().agg(F.count_if(F.col("count") > 1).alias("cands_with_many"), F.count(F.lit(1)).alias("cands"))
    return a.join(F.broadcast(c))
