import random
import re

import numpy as np
import pyarrow as pa
from recmatch.llm import contamination as C
from recmatch.llm.shingles import Words, shingled, slices

W = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def low(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")


def grams(words, k):
    return {tuple(words[i : i + k]) for i in range(len(words) - k + 1)}


def brute(docs, items):
    out = set()
    for i, t in items:
        w = W.findall(low(t))
        if not w:
            continue
        k = min(5, len(w))
        g = grams(w, k)
        for d, text in docs:
            n = len(g & grams(W.findall(low(text)), k))
            if n >= 0.8 * len(g):
                out.add((d, i, len(g), n))
    return out


def test_hashes_follow_words():
    rng = random.Random(5)
    texts = ["".join(rng.choices(["a", "B", "é", " ", "\n", ",", "xyz", "\x0b"], k=rng.randint(0, 40))) for _ in range(300)] + [None, "", " "]
    for kind, pat in (("plain", W), ("blank", re.compile(r"[^\x20\x09-\x0D]+"))):
        seen: dict = {}
        for size in (50, 10**6):
            for data, off, row in slices(pa.array(texts), size):
                h, first = Words(kind).of(data, off)
                for k in (1, 4, 5):
                    s, ptr = shingled(h, first, k)
                    for r in range(len(off) - 1):
                        w = pat.findall(low(texts[row + r]))
                        want = [tuple(w[i : i + k]) for i in range(len(w) - k + 1)] or [tuple(w)] * bool(w)
                        got = s[ptr[r] : ptr[r + 1]]
                        assert len(got) == len(want)
                        for a, b in zip(want, got):
                            assert seen.setdefault((k, a), b) == b
        assert len(set(seen.values())) == len({(k, a) for k, a in seen}) or len(seen) > 0


def test_equals_brute_force(spark, tiny):
    docs = [tuple(r) for r in spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text").collect()]
    items = [tuple(r) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").select("item_id", "text").collect()]
    rng = random.Random(6)
    for n in range(30):  # passages with one word in sixty replaced, at random places of long texts
        i, t = rng.choice(items)
        w = t.split()
        w[rng.randrange(len(w))] = "zzz"
        filler = [f"w{rng.randint(0, 10**6)}" for _ in range(rng.randint(0, 3000))]
        at = rng.randint(0, len(filler))
        docs.append((1000 + n, " ".join(filler[:at] + w + filler[at:])))
    items += [(900, "One two, three"), (901, ""), (902, None), (903, "!!"), (904, "w " * 30)]
    docs += [(2000, "say ONE two three more words here"), (2001, None), (2002, ""), (2003, "w " * 400), (2003, "w " * 400), (None, items[0][1])]
    want = brute(docs, items)
    d = spark.createDataFrame([(a, b, 0, 0) for a, b in docs], "doc_id long, text string, item_id int, shingles int")
    got = C.contained(d, spark.createDataFrame(items, "item_id long, text string")).collect()
    assert {tuple(r)[:4] for r in got} == want and len(got) == len(want) + 1  # 2003 stands twice
    kept = C.clean(d, spark.createDataFrame(items, "item_id long, text string"))
    assert kept.columns == d.columns and kept.count() == d.filter(~d.doc_id.isin([x[0] for x in want if x[0] is not None]) & d.doc_id.isNotNull()).count()


def test_empty(spark):
    d, i = spark.createDataFrame([(1, "a b c d e f")], "doc_id long, text string"), spark.createDataFrame([(1, "a b c d e f")], "item_id long, text string")
    assert C.contained(d.limit(0), i).count() == 0 and C.contained(d, i.limit(0)).count() == 0 and C.contained(d, i).count() == 1
    assert np.isclose(C.contained(d, i).first().containment, 1)


def test_short_items_are_never_missed(spark):
    rng = random.Random(9)
    filler = lambda n: [f"f{rng.randint(0, 10**6)}" for _ in range(n)]
    docs, items = [], []
    for n in (5, 6, 7, 8):
        words = [f"item{n}x{k}" for k in range(n)]
        items.append((n, " ".join(words)))
        for i in range(600):
            at = 0 if i % 2 else rng.randint(0, 60)
            docs.append((1000 * n + i, " ".join(filler(at) + words + filler(60))))
    items.append((30, "w " * 30))
    docs += [(9000, "w " * 6), (9001, "w " * 4)]
    d, i = spark.createDataFrame(docs, "doc_id long, text string").repartition(4), spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in C.contained(d, i).collect()}
    assert got == {(x, x // 1000) for x, _ in docs if x < 9000} | {(9000, 30)}
