"""Truth and comparisons of the document workloads: right, and not the work of a single task."""

import threading

import duckdb
import pytest
from recmatch.plans import candidates as C
from recmatch.plans.workloads import GRAMS, WORKLOADS, dialect
from recmatch.sources.tables import plain


@pytest.mark.parametrize("key", ("w3", "w4"))
def test_truth_of_documents_equals_its_sql_and_uses_all_cores(spark, tiny, key):
    w = WORKLOADS[key]
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    want = con.execute(f"with documents_grams as ({GRAMS['oracle']}) {plain(dialect(w.truth, 'oracle'))}").fetchall()
    got = C.side(spark, tiny, w, "truth")
    assert want and sorted(map(tuple, got.collect())) == sorted(want)
    assert "RoundRobinPartitioning" in got._jdf.queryExecution().executedPlan().toString()
    d1, d2 = C.side(spark, tiny, w, "d1"), C.side(spark, tiny, w, "d2")
    pairs = got.selectExpr("anchor_id", "cand_id", "1 as pos")
    assert C.compared(pairs, d1, d2, w).rdd.getNumPartitions() == spark.sparkContext.defaultParallelism


def test_a_joined_second_side_is_stored_once(spark, tiny):
    one, again = (C.records(spark, tiny, "w8") for _ in range(2))
    plan = one._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and one.inputFiles() and one.inputFiles() == again.inputFiles()
    assert sorted(one.collect()) == sorted(C.side(spark, tiny, C.WORKLOADS["w8"], "d2").collect())


def test_small_workloads_go_at_once_and_large_ones_one_by_one(spark, tiny, monkeypatch):
    met = threading.Barrier(2)

    def make(key):
        met.wait(60)  # breaks unless both are here
        return key, spark.range(int(key[1:])).count()

    assert C.together(spark, tiny, ["w3", "w1"], make) == [("w3", 3), ("w1", 1)]
    monkeypatch.setattr(C, "SMALL", 0)
    names = []
    assert C.together(spark, tiny, ["w3", "w1"], lambda k: names.append(threading.current_thread().name) or k) == ["w3", "w1"]
    assert names == [threading.current_thread().name] * 2 and C.tokens(spark, tiny, "w1") is None


def test_texts_are_tokenized_once_for_all_anchors(spark, tiny):
    one, again = (C.tokens(spark, tiny, "w3") for _ in range(2))
    assert one.inputFiles() and one.inputFiles() == again.inputFiles()
    d2, w = C.records(spark, tiny, "w3"), WORKLOADS["w3"]
    assert sorted((r.rid, sorted(r.toks)) for r in one.collect()) == sorted((r.rid, sorted(r.toks)) for r in C.token_lists(d2, w).collect())
