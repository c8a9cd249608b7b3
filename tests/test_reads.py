"""Queries that once made their rows up, held against their SQL on the given tables that they read now."""

import duckdb
import pytest
import __spark_entry__ as E
from pyspark.sql import functions as F
from recmatch.functions import prompts as P

NAMES = [
    "match_parse",
    "compare_parse",
    "select_parse",
    "op_udf_arrow",
    "op_udf_pandas",
    "op_udf_scalar",
    "cost_closed_forms",
    "cost_gpu",
    "op_recursive_cte",
    "op_udtf_triples",
]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_equals_its_sql(spark, tiny, name):
    df = E.queries()[name](spark, tiny)
    assert df.inputFiles()
    con = duckdb.connect()
    for t in ("documents", "events", "lineitem", "orders"):
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    cur = con.execute(E.oracle_sql()[name])
    names = [c[0] for c in cur.description]
    assert sorted(names) == sorted(df.columns)
    want = cur.fetchall()
    assert want and sorted(map(str, map(tuple, df.select(*names).collect()))) == sorted(map(str, want))


def test_parsers_on_odd_answers(spark):
    answers = ["Yes", "No.", "yes, they are the same", "I think no", "Yes or no?", "", "notable", "A", "Answer: B", "A or B", "3", "option 12", "0", "none", "00000000012", "99999999999", None]
    t = spark.createDataFrame(list(enumerate(answers)), "n int, answer string")
    got = t.select("n", P.parse_yes_no(F.col("answer")), P.parse_ab(F.col("answer")), P.parse_choice(F.col("answer"), F.lit(10))).orderBy("n").collect()
    assert [r[1] for r in got] == [True, False, True, False] + [None] * 13
    assert [r[2] for r in got] == [None] * 7 + ["A", "B"] + [None] * 8
    assert [r[3] for r in got] == [None] * 10 + [3, None, 0] + [None] * 4
