import zlib
from collections import Counter

import corpus_pipeline as P
import numpy as np
from recmatch.llm import jaccard, mixing, quality, records
from recmatch.llm.common import documents, rested

from .test_contamination import brute as leaks
from .test_jaccard import brute as groups
from .test_quality import brute as counts


def test_stages_equal_brute_force(spark, tiny):
    docs = documents(spark, tiny)
    rows = {r.doc_id: r for r in docs.collect()}
    bench = [tuple(r) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()]

    one = P.good(spark, docs, tiny).cache()
    model = quality.Fertility(quality.vocabulary())
    want = {i for i, r in rows.items() if not counts(r.text)[5] and quality.judge_all([r.text], [r.lang], model)[0][6]}
    assert {r.doc_id for r in one.collect()} == want and one.columns == docs.columns

    two = P.distinct(spark, one, tiny).cache()
    comp, _ = groups([(i, rows[i].text) for i in sorted(want)], jaccard.Rule(5, 80))
    want = {c for _, _, c in comp}
    assert {r.doc_id for r in two.collect()} == want

    three = P.uncontaminated(spark, two, tiny).cache()
    want -= {d for d, *_ in leaks([(i, rows[i].text) for i in want], bench)}
    assert {r.doc_id for r in three.collect()} == want

    four = P.mixed(spark, three, tiny).cache()
    taken = {r.doc_id: int(r.taken / r.size + 0.5) for r in mixing.mix(three)[0].collect() if r.size}
    got = Counter(r.doc_id for r in four.collect())
    assert got == Counter({i: n for i, n in taken.items() if n}) and four.columns == docs.columns

    five = P.tokens(spark, four, tiny).collect()
    tool, at, want_rows = records.Encoder(records.vocabulary()), 0, []
    for i in sorted(got.elements()):
        code = tool.encode([rows[i].text])[0] + np.array([1], "<u4").tobytes()
        want_rows.append((i, at, len(code) // 4, zlib.crc32(code)))
        at += len(code) // 4
    assert sorted(tuple(r) for r in five) == want_rows
    assert sorted(tuple(r) for r in P.run(spark, tiny).collect()) == want_rows


def test_names():
    assert [n for n, _ in P.STAGES] and len(P.STAGES) == 5


def test_stages_begin_with_the_heap_given_back(spark, tiny):
    sc = spark.sparkContext
    filled = [sc._jvm.java.nio.ByteBuffer.allocate(64 << 20) for _ in range(8)]
    high = sc._jvm.java.lang.Runtime.getRuntime().totalMemory()
    for a in filled:
        sc._gateway.detach(a)
    del filled
    rested(spark)
    rested(spark)
    assert sc._jvm.java.lang.Runtime.getRuntime().totalMemory() < high
