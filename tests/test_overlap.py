"""Documents that share grams: the rows of the SQL, without a join of all grams."""

import os
import random

from pyspark.sql import functions as F

from recmatch.operators import clustering as G
from recmatch.plans import candidates as C
from recmatch.plans import methods as M
from recmatch.plans import overlap as O
from recmatch.plans.workloads import GRAMS, WORKLOADS


def odd_documents(spark, path, repeat=()):
    """Copies, near copies, short, wordless and null texts, and a passage that all long ones share."""
    r = random.Random(3)
    common = " ".join(f"c{i}" for i in range(30))
    texts = [None, "", "?!", "one", "One", "one two three four", "ONE two, three four", "a b c d e", "a b c d e f", "é É ß İi", "é é ß i̇i"]
    for g in range(40):
        words = [f"w{r.randrange(10**6)}" for _ in range(120)]
        for _ in range(r.randrange(1, 6)):
            texts.append(" ".join(w for w in words if r.random() > r.choice((0, 0, 0.02, 0.1))) + " " + common)
    ids = [*range(-3, len(texts) - 3)]
    rows = [(i, t) for i, t in zip(ids, texts)] + [(None, "a b c d e"), *repeat]
    rows = [(i, t, "en", "s", len(t or "")) for i, t in rows]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    return str(path)


def spied(monkeypatch):
    seen, real = [], O.passing

    class Loud:
        def __init__(self, *a):
            self.inner = real(*a)

        def __enter__(self):
            store = self.inner.__enter__()

            def spy(df, name):
                out = store(df, name)
                seen.append((name, out.count(), out.inputFiles()))
                return out

            return spy

        def __exit__(self, *a):
            return self.inner.__exit__(*a)

    monkeypatch.setattr(C, "passing", Loud)
    return seen


def test_truth_of_shared_grams_equals_its_sql_and_joins_no_grams(spark, tmp_path, monkeypatch):
    seen, where, w = spied(monkeypatch), odd_documents(spark, tmp_path), WORKLOADS["w3"]
    want = sorted(map(tuple, C.side(spark, where, w, "truth").collect()))
    monkeypatch.setattr(C, "side", lambda *a: 1 / 0)
    got = C.truth(spark, where, "w3")
    assert len(want) > 30 and sorted(map(tuple, got.collect())) == want
    met = next(n for name, n, _ in seen if name == "pairs")
    documents = spark.read.parquet(f"{where}/documents.parquet").count()
    assert met < documents**2 / 20  # all long ones share a passage: a join of grams meets nearly all pairs
    assert all(not os.path.exists(f.removeprefix("file://")) for _, _, files in seen for f in files)


def test_repeated_ids_are_one_document(spark, tmp_path):
    where = odd_documents(spark, tmp_path, [(8, "a b c d e f g"), (8, "h i j k l m")])
    want = sorted(map(tuple, C.side(spark, where, WORKLOADS["w3"], "truth").collect()))
    assert want and sorted(map(tuple, C.truth(spark, where, "w3").collect())) == want


def test_least_is_the_smallest_number_of_shared_grams_that_reaches_the_share():
    for percent in (30, 40, 85):
        for n in range(1, 300):
            k = O.least(percent, n)
            assert 100 * k >= percent * (n - k) and 100 * (k - 1) < percent * (n - k + 1)


def test_minhash_edges_equal_a_join_of_all_grams_and_store_none(spark, tmp_path, monkeypatch):
    where = odd_documents(spark, tmp_path)
    g = C.sql(spark, where, GRAMS["spark"])
    x, y = (g.filter("rid is not null").selectExpr(f"rid as {c}", "gram", f"n as n{c}") for c in "xy")
    j = x.join(y, "gram").filter("x <> y").groupBy("x", "y").agg(F.count("*").alias("k"), F.max("nx").alias("nx"), F.max("ny").alias("ny"))
    want = j.filter("k >= 0.4 * (nx + ny - k)").selectExpr("x", "y", "round(k / (nx + ny - k), 6) as w")
    monkeypatch.setattr(M, "sql", lambda *a: 1 / 0)  # GRAMS, which stored all grams
    got = M._dedup(spark, where)
    assert want.count() > 60 and sorted(map(tuple, got.select("src_id", "dst_id", "weight").collect())) == sorted(map(tuple, want.collect()))


def test_components_of_chains_cliques_and_loops(spark, tmp_path):
    C.shared(spark)
    edges = [(i, i + 1) for i in range(1, 200)] + [(a, b) for a in range(300, 320) for b in range(a) if b >= 300] + [(400, 400), (-5, 500), (500, -5)]
    df = spark.createDataFrame(edges, "src_id long, dst_id long")
    got = dict(map(tuple, G.connected_components(df).select("rid", "cluster_id").collect()))
    assert got == {i: 1 for i in range(1, 201)} | {i: 300 for i in range(300, 320)} | {400: 400, -5: -5, 500: -5}
