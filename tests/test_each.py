"""Queries over all workloads: the rows of their SQL, by a small plan a workload."""

import duckdb
import pytest

from recmatch.registry import ORACLES, QUERIES


@pytest.mark.parametrize("name", ("exp_blocking", "exp_main_table", "metric_mean_f1"))
def test_workloads_have_a_plan_each(spark, tiny, name):
    got = QUERIES[name](spark, tiny)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Scan parquet" not in plan
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "documents", "pages", "benchmark"):
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    cur = con.execute(ORACLES[name])
    names = [c[0] for c in cur.description]
    rows = lambda found: sorted(tuple(round(v, 3) if isinstance(v, float) else v for v in r) for r in map(tuple, found))
    key = lambda found: sorted(map(str, rows(found)))
    assert sorted(names) == sorted(got.columns) and key(got.select(*names).collect()) == key(cur.fetchall())
