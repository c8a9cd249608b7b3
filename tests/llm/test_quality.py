import base64
import random
import re

import pyarrow.parquet as pq
from recmatch.llm import quality as Q

W = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text):
    text = text or ""
    words = W.findall(text)
    grams = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    hit = {k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(i, i + 5)}
    lines = text.split("\n")
    dup = sum(bool(W.search(x)) and x in lines[:i] for i, x in enumerate(lines))
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(hit), len(words) < 10 or 100 * len(hit) > 20 * len(words)


def test_base_counts():
    rng = random.Random(2)
    texts = ["".join(rng.choices(["a", "b", "cé", " ", " ", "\n", "\t", "\x0c", "#", "|", " ", "\x1c"], k=rng.randint(0, 120))) for _ in range(400)]
    texts += [None, "", "\n\n", "one two three four five " * 3, "x y\nx y\n x y"]
    out = Q.judge_all(texts, [None] * len(texts), Q.Fertility(Q.vocabulary()))
    for t, o in zip(texts, out):
        assert o[:6] == brute(t), t


def test_verdicts():
    model = Q.Fertility(Q.vocabulary())
    good = "the small river runs past an old stone mill where children often play during long summer days"
    junk = " ".join(chr(0x1F300 + 7 * i) * 3 for i in range(40))
    runic = " ".join(["qxzjvkw8#~^" * 4 + str(i) for i in range(20)])
    a, b, c = Q.judge_all([good, junk, None], ["en", "en", None], model)
    assert a[6] and not b[6] and not c[6] and b[9] > 0.5
    assert Q.main_script("привет мир") == "cyrillic" and Q.main_script("你好") == "cjk"
    assert Q.judge_all([runic], [None], model)[0][8] < 3


def test_spark(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet").selectExpr("*", "source as file")
    q = Q.quality(docs)
    kept = Q.keep_good(docs)
    assert q.count() == docs.count() and kept.columns == docs.columns
    assert kept.count() == q.filter("kept").count()
    assert Q.quality(docs.limit(0)).count() == 0


def test_bands_tell_junk_from_text(tiny):
    model, rng = Q.Fertility(Q.vocabulary()), random.Random(3)
    word = lambda letters, a, b: "".join(rng.choices(letters, k=rng.randint(a, b)))
    make = {
        "hex": lambda: word("0123456789abcdef", 2, 8), "hex lines": lambda: word("0123456789abcdef", 32, 32), "digits": lambda: word("0123456789", 2, 8),
        "base64": lambda: base64.b64encode(rng.randbytes(48)).decode(), "symbols": lambda: word("#*$%&|<>!?@^~+=-", 2, 8),
        "consonants": lambda: word("bcdfghjklmnpqrstvwxz", 3, 9), "letters": lambda: word("abcdefghijklmnopqrstuvwxyz", 3, 9),
    }
    for name, f in make.items():
        texts = [" ".join(f() for _ in range(150)) for _ in range(10)]
        for lang in ("en", "fr", "de", "es", None):
            if lang == "en" or name != "letters" and not (lang is None and name == "consonants"):
                assert not any(r[6] for r in Q.judge_all(texts, [lang] * 10, model)), (name, lang)
    docs = pq.read_table(f"{tiny}/documents.parquet", columns=["text", "lang"]).to_pylist()
    out = [r for r in Q.judge_all([d["text"] for d in docs], [d["lang"] for d in docs], model) if not r[5]]
    assert len(out) > 100 and sum(r[6] for r in out) >= 0.98 * len(out)
