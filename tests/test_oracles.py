"""Queries against their oracles on the smallest tables."""

import math
import os

import duckdb
import pytest
import __spark_entry__ as E

#: One of each family; the driver compares all of them.
NAMES = ["match_score", "compare_score_probs", "select_optout", "compound_match_select", "metric_prf", "cost_records", "fewshot_examples", "match_fewshot", "cost_tokens", "cost_frontier", "exp_position", "exp_judges", "graph_mutual_best", "block_bm25_topn", "op_agg_cube", "op_join_range", "op_win_frames", "st_tumbling", "st_stream_join"]


@pytest.fixture(scope="module")
def duck(tiny):
    con = duckdb.connect()
    for f in os.listdir(tiny):
        con.execute(f"create view {f[:-8]} as select * from '{tiny}/{f}'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_parity(spark, tiny, duck, name):
    df = E.queries()[name](spark, tiny)
    cur = duck.execute(E.oracle_sql()[name])
    names = [c[0] for c in cur.description]
    assert sorted(names) == sorted(df.columns)
    tidy = lambda v: None if isinstance(v, float) and math.isnan(v) else round(v, 6) if isinstance(v, float) else v
    want = sorted((tuple(tidy(r[names.index(c)]) for c in sorted(names)) for r in cur.fetchall()), key=str)
    assert sorted((tuple(tidy(r[c]) for c in sorted(names)) for r in df.collect()), key=str) == want


def test_entry(spark):
    assert E.entry(spark).count() >= 0 and set(E.oracle_sql()) <= set(E.queries())
