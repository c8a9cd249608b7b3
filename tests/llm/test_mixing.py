from collections import defaultdict

from pyspark.sql import functions as F
from recmatch.llm import mixing as M


def level(sizes, weights=(5, 2, 1)):
    w = {s: weights[i % 3] for i, s in enumerate(sorted(sizes, key=lambda s: (s is None, (s or "").encode())))}
    out, left, open_ = {}, 1.5 * sum(sizes.values()), set(sizes)
    while open_:
        t = {s: left * w[s] / sum(w[x] for x in open_) for s in open_}
        over = {s for s in open_ if t[s] > 2 * sizes[s]}
        if not over:
            return out | t
        for s in over:
            out[s] = 2.0 * sizes[s]
            left -= out[s]
        open_ -= over
    return out


def check(docs):
    rows = M.mix(docs)[0].collect()
    src = defaultdict(list)
    for r in docs.collect():
        src[r.doc_id].append((r.source, len([w for w in __import__("re").findall(r"[^\x20\x09-\x0D]+", r.text or "")])))
    size, got = defaultdict(int), defaultdict(int)
    for v in src.values():
        for s, n in v:
            size[s] += n
    want = level(size)
    for r in rows:
        s = next(s for s, n in src[r.doc_id] if n == r.size)
        assert r.source_size == size[s] and abs(r.target - want[s]) < 1e-6 * max(1, want[s]) and 0 <= r.taken <= 2 * r.size
        got[s] += r.taken
    for s in size:
        assert abs(got[s] - want[s]) <= 0.02 * want[s] + 100, (s, got[s], want[s])
    assert len(rows) == docs.count()
    return rows


def test_mix(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    a = check(docs)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "5")
    try:
        assert [tuple(x)[1:] for x in sorted(a, key=lambda r: r.doc_id)] == [tuple(x)[1:] for x in sorted(check(docs.repartition(7)), key=lambda r: r.doc_id)]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_edges(spark):
    docs = spark.createDataFrame([(1, "a b c", None, 1), (2, None, "é", 1), (3, "", "z", 1), (4, "w " * 50000, "hot", 1), (5, "x y", "hot", 1), (5, "x y", "hot", 1)], "doc_id long, text string, source string, target int")
    docs = docs.selectExpr("*", "1 as _n", "2 as row", "3 as `a.b`")
    check(docs)
    assert M.mix(docs.limit(0))[0].count() == 0
    assert M.take(docs).columns == docs.columns


def test_schedule_is_even(spark):
    t = spark.createDataFrame([(1, "a", 10**6, 1.5e6), (2, "b", 10**6, 0.5e6), (3, "c", 10**6, 0.25e6)], "source_key int, source string, source_size long, target double")
    plan = M.schedule(t, 100, chunk=1000)
    n = plan.count()
    for start in range(0, n - 2000, 4500):
        part = {r[0]: r[1] for r in plan.filter(F.col("slot").between(start, start + 1999)).groupBy("source_key").count().collect()}
        for key, share in ((1, 1.5 / 2.25), (2, 0.5 / 2.25), (3, 0.25 / 2.25)):
            assert abs(part[key] - 2000 * share) < 12
    assert plan.groupBy("source_key").agg(F.count("*").alias("n"), F.max("block_no").alias("m"), F.countDistinct("block_no").alias("d")).filter("n <> m + 1 or n <> d").count() == 0


def test_take_moves_texts_alike_on_any_input(spark, tiny):
    """A broadcast on small inputs only would make the shuffles of larger ones look like growth."""
    out = M.take(spark.read.parquet(f"{tiny}/documents.parquet"))
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan
