"""Accuracy and cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def accepted(cands: DataFrame, decisions: DataFrame) -> DataFrame:
    """decisions (anchor_id, cand_id or null) with is_true."""
    t = cands.filter("is_true").select("anchor_id", "cand_id", F.lit(True).alias("t"))
    return decisions.filter("cand_id is not null").select("anchor_id", "cand_id").join(t, ["anchor_id", "cand_id"], "left").select("anchor_id", "cand_id", F.coalesce("t", F.lit(False)).alias("is_true"))


def rates(tp: Column, fp: Column, fn: Column) -> list[Column]:
    """precision, recall, f1 in percent, null where undefined."""
    p, r = tp / F.nullif(tp + fp, F.lit(0)), tp / F.nullif(tp + fn, F.lit(0))
    return [F.round(100 * p, 4).alias("precision"), F.round(100 * r, 4).alias("recall"), F.round(200 * tp / F.nullif(2 * tp + fp + fn, F.lit(0)), 4).alias("f1")]


def prf(cands: DataFrame, decisions: DataFrame, positives: DataFrame | None = None) -> DataFrame:
    """tp, fp, fn, precision, recall, f1. positives: one row with n, all true matches; else those that blocking kept."""
    got = accepted(cands, decisions).agg(F.count_if(F.col("is_true")).alias("tp"), F.count_if(~F.col("is_true")).alias("fp"))
    total = positives if positives is not None else cands.agg(F.count_if(F.col("is_true")).alias("n"))
    both = got.join(F.broadcast(total)).select("tp", "fp", (F.col("n") - F.col("tp")).alias("fn"))  # one row each
    return both.select("tp", "fp", "fn", *rates(F.col("tp"), F.col("fp"), F.col("fn")))


def ranking_recall(ranked: DataFrame, ks: tuple[int, ...] = (1, 3, 4, 10)) -> DataFrame:
    """Among lists that hold the true candidate, how many rank it in the first k."""
    t = ranked.filter("is_true").groupBy("anchor_id").agg(F.min("rank").alias("r"))
    return t.select(F.explode(F.array(*map(F.lit, ks))).alias("k"), "r").groupBy("k").agg(F.count(F.lit(1)).alias("lists"), F.round(F.avg((F.col("r") <= F.col("k")).cast("double")), 6).alias("recall"))


def selection_accuracy(cands: DataFrame, decisions: DataFrame) -> DataFrame:
    t = cands.groupBy("anchor_id").agg(F.min(F.when(F.col("is_true"), F.col("cand_id"))).alias("want"))
    right = F.col("want").eqNullSafe(F.col("cand_id"))
    return t.join(decisions.select("anchor_id", "cand_id"), "anchor_id").agg(F.count(F.lit(1)).alias("lists"), F.round(F.avg(right.cast("double")), 6).alias("accuracy"))


def cluster_prf(members: DataFrame, true_pairs: DataFrame) -> DataFrame:
    """Pairwise rates of clusters (rid, cluster_id) by counts: pairs in clusters, true pairs, and true pairs within one."""
    made = members.groupBy("cluster_id").count().agg(F.coalesce(F.sum(F.col("count") * (F.col("count") - 1) / 2), F.lit(0.0)).cast("long").alias("made"))
    a, b = members.select(F.col("rid").alias("a"), F.col("cluster_id").alias("ca")), members.select(F.col("rid").alias("b"), F.col("cluster_id").alias("cb"))
    t = true_pairs.join(a, "a", "left").join(b, "b", "left").agg(F.count(F.lit(1)).alias("want"), F.count_if(F.col("ca") == F.col("cb")).alias("tp"))
    one = made.join(F.broadcast(t)).select("tp", (F.col("made") - F.col("tp")).alias("fp"), (F.col("want") - F.col("tp")).alias("fn"))
    return one.select("tp", "fp", "fn", *rates(F.col("tp"), F.col("fp"), F.col("fn")))


def pareto(df: DataFrame, cost: str, gain: str) -> DataFrame:
    """Rows that no other beats in one measure without losing in the other."""
    cheap = Window.orderBy(cost, F.desc(gain)).rowsBetween(Window.unboundedPreceding, -1)  # as many rows as strategies
    best = F.max(gain).over(cheap)
    return df.withColumn("_best", best).filter(F.col("_best").isNull() | (F.col(gain) > F.col("_best"))).drop("_best")


#: Calls and records a list of n, with k kept, as SQL text; few-shot calls carry six examples of two records.
CLOSED = {
    "pairwise": ("n", "2 * n"),
    "pairwise_fewshot": ("n", "14 * n"),
    "triplewise_topk": ("k * (2 * n - k - 1)", "3 * k * (2 * n - k - 1)"),
    "triplewise_identify": ("2 * (n - 1) + 1", "6 * (n - 1) + 2"),
    "triplewise_allpair": ("n * (n - 1)", "3 * n * (n - 1)"),
    "listwise": ("1", "n + 1"),
    "listwise_verify": ("2", "n + 3"),
    "compound_match": ("n + 1", "2 * n + k + 1"),
    "compound_bubble": ("k * (2 * n - k - 1) + 1", "3 * k * (2 * n - k - 1) + k + 1"),
    "compound_allpair": ("n * (n - 1) + 1", "3 * n * (n - 1) + k + 1"),
}


def expected(strategy: str, n: int, k: int = 4) -> tuple[int, int]:
    """The closed forms in numbers."""
    calls, records = (eval(x, {}, {"n": n, "k": min(k, n)}) for x in CLOSED[strategy])  # noqa: S307  fixed text above
    return calls, records
