import random
import zlib
from collections import defaultdict
from itertools import product

from recmatch.llm import sharding as S


def loads(weights, k):
    out = [0] * k
    for w, e in zip(weights, S.difference([(w,) + (0,) * (k - 1) for w in weights], k)):
        out[e[0]] += w
    return out


def test_differencing():
    assert S.difference([], 3) == []
    assert sorted(loads([8, 7, 6, 5, 4], 2)) == [14, 16]  # the known result of differencing; the best is 15, 15
    rng = random.Random(4)
    for _ in range(200):
        w = [rng.randint(1, 50) for _ in range(rng.randint(1, 7))]
        got = loads(w, 3)
        best = min(max(sum(x for x, s in zip(w, a) if s == b) for b in range(3)) for a in product(range(3), repeat=len(w)))
        assert sum(got) == sum(w) and best <= max(got) <= best * 4 / 3 + 1
    w = [rng.randint(1, 10**6) for _ in range(5000)]
    got = loads(w, 8)
    assert max(got) - min(got) < 50


def test_partial_partitions_keep_their_slots_apart():
    parts = [(5, 1, 0), (0, 4, 4), (3, 3, 3)]
    for e in S.difference(parts, 3):
        assert sorted(e) == [0, 1, 2]


def test_shards(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet").selectExpr("doc_id", "text", "source as shard")
    more = spark.createDataFrame([(900, None, "x"), (901, None, "x"), (902, "", "x"), (902, "", "x"), (None, "é", "x")], docs.schema)
    docs = docs.union(more)
    rows = S.shard(docs).collect()
    assert len(rows) == docs.count() and sorted(map(tuple, rows), key=str) == sorted(map(tuple, S.shard(docs.repartition(5)).collect()), key=str)
    slots, texts = defaultdict(list), defaultdict(set)
    byte = defaultdict(int)
    want = defaultdict(list)
    for i, t, _ in docs.collect():
        want[i].append((len((t or "").encode()) + 1, zlib.crc32((t or "").encode()), t))
    for r in rows:
        slots[r.shard].append(r.slot)
        byte[r.shard] += r.size
        assert (r.size, r.text_crc32) in [w[:2] for w in want[r.doc_id]]
        texts[(r.size, r.text_crc32)].add(r.shard)
    assert all(sorted(x) == list(range(len(x))) for x in slots.values()) and set(slots) <= set(range(8))
    assert all(len(x) == 1 for k, x in texts.items() if k[0] > 1)
    assert max(byte.values()) - min(byte.values()) < 0.02 * sum(byte.values()) / 8
    assert S.shard(docs.limit(0)).count() == 0
