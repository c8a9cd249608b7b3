import itertools
import random
import re

from recmatch.llm import licenses as L

W = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute(text):
    w = W.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    at, labels = [], set()
    for p, label in L.PHRASES:
        q = p.split()
        here = [i for i in range(len(w) - len(q) + 1) if w[i : i + len(q)] == q]
        at += here
        labels |= {label} if here else set()
    return len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels))


def test_base_and_labels(spark, tiny):
    rng = random.Random(7)
    bits = ["cc", "CC", "by", "-", " ", " ", "all", "rights", "Reserved", "general", "public", "license", "xé", "K", "İ", "licensed under the GNU", ", version 3."]
    rows = [(i, "".join(x + rng.choice([" ", "", "-"]) for x in rng.choices(bits, k=rng.randint(0, 30)))) for i in range(400)]
    rows += [(1000 + r.doc_id, r.text) for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()]
    notices = {
        5001: ("This work is licensed under the GNU General Public License, version 3.", "gpl,gpl-3.0"),
        5002: ("Released under the MIT License.", "mit"),
        5003: ("x " * 5000 + "Licensed under the Apache License, Version 2.0. " + "y " * 50, "apache-2.0"),
        5004: ("Licensed under CC BY-NC 4.0.", "cc-by,cc-by-nc-4.0"),
        5005: ("Permission is hereby granted, free of charge, to any one obtaining a copy of this software and associated documentation files", "mit"),
        5006: ("the apache tribe had a license, version unknown", ""),
        5007: (None, ""),
        5008: ("", ""),
    }
    rows += [(k, v[0]) for k, v in notices.items()] + [(5002, notices[5002][0])]
    docs = spark.createDataFrame([(a, b, 1, "z") for a, b in rows], "doc_id long, text string, w int, label string").repartition(4)
    got = L.scan(docs).collect()
    assert len(got) == len(rows)
    want = {}
    for a, b in rows:
        want.setdefault(a, []).append(brute(b))
    for r in got:
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) in want[r.doc_id], r
        assert 0 <= r.score <= 1 and set(r.base_labels.split(",")) - {""} <= set(r.labels.split(","))
        if r.doc_id in notices:
            assert r.labels == notices[r.doc_id][1], r
    assert L.scan(docs.limit(0)).count() == 0


def notice_labels(text):
    """Every template at every place, without an index."""
    w = W.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    found, best = set(), 0.0
    for label, t, phrases in L.TEMPLATES:
        t = t.split()
        for i in range(len(w)):
            part = w[i : i + len(t)]
            score = sum(a == b for a, b in zip(part, t)) / len(t)
            if score >= L.LEAST_SCORE and all(f" {p} " in f" {' '.join(part)} " for p in phrases):
                found.add(label)
                best = max(best, score)
    return found, best


def test_notices_equal_brute_force(spark):
    rng = random.Random(11)
    texts = ["\n".join(a + " ." for _, a, _ in pair) for pair in itertools.product(L.TEMPLATES, repeat=2)]
    texts += [" ".join(t for _, t, _ in L.TEMPLATES), "Redistributions and use" + L.TEMPLATES[7][1][len("redistribution and use") :], " ".join(L.vocabulary()) + " " + L.TEMPLATES[4][1]]
    for _ in range(200):  # notices with some words replaced, among other words of the vocabulary
        w = []
        for _, t, _ in rng.sample(L.TEMPLATES, rng.randint(1, 3)):
            part = t.split()
            for k in rng.sample(range(len(part)), min(len(part), rng.randint(0, 4))):
                part[k] = "zzz"
            w += rng.choices(L.vocabulary(), k=rng.randint(0, 20)) + part
        texts.append(" ".join(w))
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(4)
    got = {r.doc_id: r for r in L.scan(docs).collect()}
    for i, t in enumerate(texts):
        found, score = notice_labels(t)
        assert set(got[i].labels.split(",")) - {""} == found | set(brute(t)[4].split(",")) - {""}, t
        assert abs(got[i].score - score) < 1e-9, t
