import random
import zlib

import numpy as np
import pytest
from recmatch.llm import records as R
from recmatch.llm.common import scratch


def reference(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(R.vocabulary())
    return [np.array(t.encode(x, add_special_tokens=False).ids, "<u4").tobytes() for x in texts]


def test_piecewise_equals_library(spark, tiny):
    texts = [r[0] for r in spark.read.parquet(f"{tiny}/documents.parquet").select("text").collect()]
    rng = random.Random(1)
    signs = list("abcXYZÀéß'stmd 019.,!?-_\t\n\r\x0b<|>#@İſΣσ中 ́\x1c\x85") + ["<|endoftext|>", "'ll", "'S"]
    texts += ["".join(rng.choices(signs, k=rng.randint(0, 60))) for _ in range(3000)] + ["", " ", "a" * 5000]
    assert R.Encoder(R.vocabulary()).encode(texts) == reference(texts)


def test_frames():
    data = R.frame(b"abc")
    assert R.unframe(data) == b"abc" and len(data) == 19
    for i in range(len(data)):
        with pytest.raises(ValueError):
            R.unframe(data[:i] + bytes([data[i] ^ 1]) + data[i + 1 :])
    assert R.unpack(R.pack(None, np.array([1, 70000], np.uint32), 4))[0] is None


def test_round_trip_and_shuffled_reads(spark):
    rows = [(3, "Hello there", "x"), (1, None, "x"), (2, "", None), (3, "Hello there", "y"), (None, "a b", "z"), (9, "w " * 20000, "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, file string")
    where = scratch(spark, "t")
    got = {tuple(r) for r in R.digest(docs, where).collect()}
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    want, at = set(), 0
    for r, code in zip(order, reference([r[1] or "" for r in order])):
        code += np.array([1], "<u4").tobytes()
        want.add((r[0], at, len(code) // 4, zlib.crc32(code)))
        at += len(code) // 4
    assert got == want and len(got) == 6
    index = spark.read.parquet(f"{where}/index")
    assert R.read_records(index.orderBy("length"), where).count() == 6


def test_empty(spark):
    assert R.digest(spark.createDataFrame([], "doc_id long, text string"), scratch(spark, "t")).count() == 0


def test_words_outlive_a_full_cache_and_cost_no_call_of_the_library(monkeypatch):
    monkeypatch.setattr(R, "CACHED_WORDS", 8)
    tool = R.Encoder(R.vocabulary())
    monkeypatch.setattr(tool, "whole", lambda text: pytest.fail(f"{text!r} went to the library"))
    texts = [f"The naïve café's İstanbul, don't «x²» 3½ Ⱥb {'z' * 50} w{n} {n}e'll" for n in range(40)]
    want = reference(texts)
    assert [x for t in texts for x in tool.encode([t])] == [x for x in want if x is not None]
    assert len(tool.cache) + len(tool.older) < 60 and "café's" in tool.cache


def test_a_short_piece_is_tokenized_once(monkeypatch):
    tool = R.Encoder(R.vocabulary())
    calls, piece = [], tool.piece
    monkeypatch.setattr(tool, "piece", lambda text: calls.append(text) or piece(text))
    texts = [" ".join(f"{a}{b}{n}!" for n in range(10)) for a in "abc" for b in "xyz"] + ["", " \t\n ", "one"]
    assert tool.encode(texts) == reference(texts)
    assert calls.count("!") == 1 and len(calls) == len(set(calls))
