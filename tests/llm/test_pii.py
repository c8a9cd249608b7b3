import hashlib
import random
import re

from recmatch.llm import pii as P

RULES = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m[0].split("."))),
    ("card", r"[0-9]([\x20-]?[0-9])+", lambda m: 14 <= len(d := re.sub(r"[^0-9]", "", m[0])) <= 19 and P.luhn([int(c) for c in d])),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 10 <= len(re.sub(r"[^0-9]", "", m[0])) <= 15),
]


def brute(text):
    out = sorted((m.start(), k, m.end()) for k, (_, p, ok) in enumerate(RULES) for m in re.finditer(p, text or "") if ok(m))
    return [(a, k, b) for a, k, b in out]


def test_base_equals_patterns(spark, tiny):
    rng = random.Random(3)
    bits = ["1", "22", "4539578763621486", "255", "300", ".", ".", "-", " ", "@", "a", "b.c", "+", "+1", "(", ")", "é", "٣", "%", "ab@cd.ef", "İ", "\n"]
    texts = ["".join(rng.choices(bits, k=rng.randint(0, 25))) for _ in range(6000)]
    texts += [r[0] for r in spark.read.parquet(f"{tiny}/documents.parquet").select("text").collect()]
    a = P.Anchors()
    assert [s for s in a.spans("x " + "0" * 5000 + ".1.1.1") if s[1] == 1] == [(2, 1, 5008)] and not [s for s in a.spans("9" * 5000 + ".1.1.1") if s[1] == 1]
    for t in texts:
        assert [s for s in a.spans(t) if s[1] < 4] == brute(t), t


def test_method_spans():
    a = P.Anchors()
    kinds = lambda t: {P.KINDS[k]: t[s:e] for s, k, e in a.spans(t)}
    assert kinds("see https://bob:pw@host.example/x?id=3.")["url"] == "https://bob:pw@host.example/x?id=3"
    assert kinds("pay DE89 3704 0044 0532 0130 00 now")["iban"] == "DE89 3704 0044 0532 0130 00"
    assert "iban" not in kinds("pay DE88 3704 0044 0532 0130 00 now")
    assert kinds("Account no: AB-1234567 closed")["account"] == "AB-1234567"
    assert kinds("jo.doe [at] mail [dot] example")["spelled"] == "jo.doe [at] mail [dot] example"
    assert not a.spans("a clean line about an account of the war in 1918, at 5 o'clock")
    assert P.masked_text("to a@b.cd or +1 555 123 4567") == "to <email> or <phone>"


def test_rows(spark):
    docs = spark.createDataFrame([(1, None, 1), (1, None, 1), (2, "x@y.zz " * 20000, 2), (None, "", 3)], "doc_id long, text string, spans int")
    got = {(r.doc_id, r.n_email, r.n_spans) for r in P.find(docs).collect()}
    assert got == {(1, 0, 0), (2, 20000, 20000), (None, 0, 0)} and P.find(docs).count() == 4
    assert P.find(docs).first().base_sha256 == hashlib.sha256(b"").hexdigest()
    assert P.find(docs.limit(0)).count() == 0
