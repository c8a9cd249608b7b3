"""Token blocking scored where records are read, against pairs counted one by one."""

import math
from dataclasses import replace

import pytest

from recmatch.plans import blocking as B
from recmatch.plans.workloads import WORKLOADS

W = replace(WORKLOADS["w1"], max_df=0.5, blocked_on=("name",))


def brute(anchors, records, n, exclude_self=False):
    tokens = {r: set(t.split()) for r, t in records}
    df = {}
    for ts in tokens.values():
        for t in ts:
            df[t] = df.get(t, 0) + 1
    out = []
    for a, text in anchors:
        has = {t for t in text.split() if df.get(t, len(tokens)) <= W.max_df * len(tokens)}
        met = [(-round(sum(math.log(len(tokens) / df[t]) for t in sorted(has & ts)), 6), r) for r, ts in tokens.items() if has & ts and not (exclude_self and r == a)]
        out += [(a, r, i, -s) for i, (s, r) in enumerate(sorted(met)[:n], 1)]
    return sorted(out)


RECORDS = [(i, f"w{i % 7} v{i % 11} u{i % 3 * (i % 2)}" + (" x" if i % 5 == 0 else "")) for i in range(300)] + [(300, "")]


@pytest.mark.parametrize("at_once", (2000, 3))
def test_equals_pairs_counted_one_by_one_and_shuffles_none(spark, monkeypatch, at_once):
    monkeypatch.setattr(B, "PASS", at_once)
    d2 = spark.createDataFrame(RECORDS, "rid long, name string")
    anchors = [(1000 + i, f"w{i} v{i} x nowhere") for i in range(8)]
    got = B.block_tfidf(spark.createDataFrame(anchors, "rid long, name string"), d2, W, 4)
    assert sorted(map(tuple, got.collect())) == brute(anchors, RECORDS, 4)
    assert "Join" not in got._jdf.queryExecution().toString().split("Physical Plan")[1]


def test_a_collection_with_itself_meets_by_token_sets(spark):
    d = spark.createDataFrame(RECORDS, "rid long, name string").repartition(5)
    asked = []
    keep = lambda name, make: asked.append(name) or make().localCheckpoint()
    got = B.block_same(d, W, 4, keep)
    assert sorted(map(tuple, got.collect())) == brute(RECORDS, RECORDS, 4, True) and asked == ["sets", "near"]
