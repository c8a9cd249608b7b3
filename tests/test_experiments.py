"""What the experiments promise: costs as rendered, orderings of methods, baselines that learn."""

import pytest
from pyspark.sql import functions as F

from recmatch.functions import prompts as P
from recmatch.operators import baselines as BL
from recmatch.operators import measures as A
from recmatch.plans import experiments as X
from recmatch.plans.candidates import anchors, candidates
from recmatch.registry import QUERIES


def test_words_of_questions_are_those_rendered(spark):
    t = spark.createDataFrame([("name: a b; size: 3", "name: c", "brand: d e f")], "g string, x string, y string")
    n = lambda c: P.count_tokens(c)
    g, x, y = F.col("g"), F.col("x"), F.col("y")
    r = t.select(
        (n(P.render_pair(g, x)) - n(g) - n(x)).alias("pair"), (n(P.render_triple(g, x, y)) - n(g) - n(x) - n(y)).alias("triple"),
        (n(P.render_list(g, F.array(x, y), False)) - n(g) - n(x) - n(y) - 2).alias("list"), (n(P.render_list(g, F.array(x, y), True)) - n(P.render_list(g, F.array(x, y), False))).alias("none"),
        (n(P.render_example(g, x, F.lit(1))) - n(g) - n(x)).alias("example"),
    ).first()
    assert tuple(r) == (P.PAIR_WORDS, P.TRIPLE_WORDS, P.LIST_WORDS, P.NONE_WORDS, P.EXAMPLE_WORDS)


def test_costs_order_as_published(spark, tiny):
    r = {x.strategy: x.ratio for x in QUERIES["cost_ratio"](spark, tiny).collect()}
    assert set(r) == set(A.CLOSED) and r["pairwise"] == 1
    assert r["listwise"] < 0.5 and r["triplewise_identify"] > 2 and r["compound_match"] < r["listwise"] < r["pairwise_fewshot"]


def test_matching_ranks_better_than_comparing_at_every_size(spark, tiny):
    r = {(x.judge, x.ranker): x.recall for x in QUERIES["exp_rank_recall"](spark, tiny).collect()}
    sizes = [f"size {i}" for i in range(1, 9)]
    assert all(r[s, "pairwise"] >= r[s, "allpair"] for s in sizes)
    gap = [r[s, "pairwise"] - r[s, "allpair"] for s in sizes]
    assert max(gap[-2:]) < 0.05 < min(gap[:4])


def test_place_bias_by_position(spark, tiny):
    f1 = {(x.method, x.slot): x.f1 for x in QUERIES["exp_position"](spark, tiny).collect()}
    drop = lambda m: f1[m, 1] - f1[m, 10]
    assert drop("unbiased") == 0 and drop("listwise") > drop("compound") >= 0 and drop("triplewise") > 0


@pytest.mark.parametrize("name", list(X.BASELINES))
def test_baselines_beat_chance_and_repeat(spark, tiny, name):
    c = candidates(spark, tiny, "w2")
    everything = A.prf(c, c.select("anchor_id", "cand_id")).first().f1
    one = X.baseline(spark, tiny, "w2", name)
    assert A.prf(c, BL.decide(one)).first().f1 > everything
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, X.baseline(spark, tiny, "w2", name).collect()))


def test_baselines_without_training_pairs(spark, tiny, monkeypatch):
    c = candidates(spark, tiny, "w2")
    monkeypatch.setattr(X.M, "training_pairs", lambda *_: c.limit(0))
    for name in ("supervised", "list-aware", "mixture"):
        assert X.baseline(spark, tiny, "w2", name).filter("p <> 0").isEmpty()


def test_sizes_of_a_workload_keep_repeats_and_nulls_apart(spark):
    d1 = spark.createDataFrame([(1,), (2,), (2,), (None,)], "rid long")
    d2 = spark.createDataFrame([(10,), (20,), (20,), (None,)], "rid long")
    true = spark.createDataFrame([(1, 10), (2, 10), (2, 20), (2, 30), (3, 20), (1, None), (None, 10)], "anchor_id long, cand_id long")
    assert X.sizes(d1, d2, true) == (4, 4, 3)
    assert X.sizes(d1.limit(0), d2.limit(0), true) == (0, 0, 0)


def test_examples_are_searched_among_stored_training_anchors(spark, tiny):
    ids = lambda df, c: {r[0] for r in df.select(c).collect()}
    rest, again = (X.M.training_anchors(spark, tiny, "w2") for _ in range(2))
    assert rest.inputFiles() and rest.inputFiles() == again.inputFiles()
    assert ids(X.M.training_pairs(spark, tiny, "w2"), "anchor_id") <= ids(rest, "rid")
    assert not ids(rest, "rid") & ids(anchors(spark, tiny, "w2"), "rid")
    assert ids(X.M.examples(spark, tiny, "w2"), "ex_a") <= ids(rest, "rid")
