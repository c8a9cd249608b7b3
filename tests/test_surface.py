"""Relational operators on rows that the given tables do not hold, and how they are planned."""

import __spark_entry__ as E


def test_lateral_takes_the_dearest_of_every_customer_that_orders_name(spark, tmp_path):
    rows = [(100 * c + k, c if c else None, float((37 * k) % 11)) for c in range(40) for k in range(9)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double").repartition(7).write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(c,) for c in range(20)], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    df = E.queries()["op_join_lateral"](spark, str(tmp_path))
    want = {(c, k) for c in {r[1] for r in rows} for _, k in sorted((-p, k) for k, o, p in rows if o == c)[:2]}
    assert sorted(map(str, map(tuple, df.collect()))) == sorted(map(str, want))
    assert "o_totalprice" in next(x for x in df._jdf.queryExecution().toString().split("Physical Plan")[1].split("\n") if " Window " in x)


def test_streams_leave_their_rows_in_files_not_on_the_driver(spark, tiny):
    for name in ("st_session", "st_tumbling", "st_sliding", "st_stateful_canon"):
        assert E.queries()[name](spark, tiny).inputFiles()


def test_salted_join_broadcasts_no_copies(spark, tiny):
    assert "Broadcast" not in E.queries()["op_join_skew_salted"](spark, tiny)._jdf.queryExecution().toString()
