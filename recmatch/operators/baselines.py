"""Learned baselines on pair features, of the families that the experiments compare with."""

from __future__ import annotations

from pyspark.ml import Pipeline
from pyspark.ml.classification import GBTClassifier, LogisticRegression
from pyspark.ml.clustering import GaussianMixture
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def features(cands: DataFrame) -> list[str]:
    return [c for c in cands.columns if c.startswith("s_")]


def pair_features(cands: DataFrame, context: bool = False) -> DataFrame:
    """Similarities with 0.5 where a side lacks the attribute; context adds what rivals look like: rank and gap to the best."""
    out = cands.na.fill(0.5, features(cands)).withColumn("label", F.col("is_true").cast("double"))
    if context:
        w = Window.partitionBy("anchor_id")
        out = out.withColumn("s_gap", F.max("sim").over(w) - F.col("sim")).withColumn("s_rank", F.rank().over(w.orderBy(F.desc("sim"))) / 10.0).withColumn("s_first", 1 / F.col("pos"))
    return out


def _fit(train: DataFrame, stage) -> object:
    return Pipeline(stages=[VectorAssembler(inputCols=features(train), outputCol="features"), stage]).fit(train)


def fit_pair_classifier(train: DataFrame):
    return _fit(train, LogisticRegression(maxIter=30, regParam=0.001))


def fit_context_classifier(train: DataFrame):
    return _fit(train, GBTClassifier(maxIter=15, maxDepth=4, seed=3))


def fit_mixture(pairs: DataFrame):
    """Two components over similarities, without labels; the one with the larger means is the matches'."""
    return _fit(pairs, GaussianMixture(k=2, seed=3, maxIter=40))


def fit_selfsup(records_pairs: DataFrame):
    """records_pairs: features of records with a perturbed copy of themselves (label 1) and with others (label 0)."""
    return _fit(records_pairs, LogisticRegression(maxIter=30, regParam=0.01))


def predict(model, pairs: DataFrame) -> DataFrame:
    """anchor_id, cand_id, p."""
    out = model.transform(pairs)
    p = vector_to_array("probability")
    if hasattr(model.stages[-1], "gaussiansDF"):
        means = [sum(r["mean"]) for r in model.stages[-1].gaussiansDF.select("mean").collect()]  # two rows
        return out.select("anchor_id", "cand_id", p[means.index(max(means))].alias("p"))
    return out.select("anchor_id", "cand_id", p[1].alias("p"))


def decide(scored: DataFrame) -> DataFrame:
    return scored.filter("p >= 0.5").select("anchor_id", "cand_id")


def fit_threshold(train: DataFrame) -> DataFrame:
    """One row: the similarity from which on accepting gives the best F1, by running counts over distinct values."""
    by = train.groupBy("sim").agg(F.count_if("is_true").alias("t"), F.count(F.lit(1)).alias("n"))
    down = Window.orderBy(F.desc("sim")).rowsBetween(Window.unboundedPreceding, 0)  # similarities have six digits, so rows are bounded
    all_true = train.agg(F.count_if("is_true").alias("all"))
    run = by.withColumn("tp", F.sum("t").over(down)).withColumn("got", F.sum("n").over(down)).join(F.broadcast(all_true))
    run = run.withColumn("f1", F.round(200 * F.col("tp") / (F.col("got") + F.col("all")), 4))
    return run.orderBy(F.desc("f1"), F.desc("sim")).limit(1).select(F.col("sim").alias("threshold"), "f1")
