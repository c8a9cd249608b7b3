import numpy as np
import pytest
from pyspark.sql import functions as F

from recmatch.plans import blocking
from recmatch.registry import QUERIES


@pytest.mark.parametrize("sf", ("sf0.001", "sf0.01", "sf0.1"))
def test_vector_index_finds_the_neighbours(spark, sf):
    exact = QUERIES["block_vector_topn"](spark, f"/root/testdata/{sf}").select("anchor_id", "cand_id")
    near = QUERIES["block_vector_lsh"](spark, f"/root/testdata/{sf}").select("anchor_id", F.col("cand_id"), F.lit(1).alias("found"))
    recall = exact.join(near, ["anchor_id", "cand_id"], "left").agg(F.avg(F.coalesce("found", F.lit(0)))).first()[0]
    print(sf, recall)
    assert recall >= 0.9


@pytest.mark.parametrize("planes", (0, 3))
def test_vectors_are_scored_where_they_are_read(spark, planes, monkeypatch):
    monkeypatch.setattr(blocking, "PASS", 7)
    rng = np.random.default_rng(3)
    v = rng.normal(size=(60, 6)).astype(np.float32)[rng.integers(0, 60, 5000)]  # many ties
    v[4] = 0
    rows = [(i, None if i == 9 else x.tolist()) for i, x in enumerate(v)]
    d = spark.createDataFrame(rows, "rid long, v array<float>").repartition(5)
    found = blocking.block_vectors(d.filter("rid % 500 = 0"), d, 10, planes, reach=planes)
    plan = found._jdf.queryExecution().toString()
    assert "Join" not in plan and "CartesianProduct" not in plan
    unit = v.astype(float) / np.maximum(np.sqrt((v.astype(float) ** 2).sum(1, keepdims=True)), 1e-300)
    want = set()
    for a in range(0, 5000, 500):
        scores = np.round(unit @ unit[a], 6)
        want |= {(a, int(c), n, round(float(scores[c]), 6)) for n, c in enumerate(sorted((i for i in range(5000) if i not in (4, 9)), key=lambda i: (-scores[i], i))[:10], 1)}
    assert {(*r[:3], round(r[3], 6)) for r in map(tuple, found.collect())} == want


def test_vectors_without_length_come_last(spark):
    d = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 0.0]), (2, [0.0, 2.0]), (3, None)], "rid long, v array<double>")
    assert sorted(map(tuple, blocking.block_vectors(d.filter("rid = 0"), d).collect())) == [(0, 0, 1, 1.0), (0, 1, 3, None), (0, 2, 2, 0.0)]
