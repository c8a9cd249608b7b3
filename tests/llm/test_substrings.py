import bisect
import hashlib
import random
from collections import Counter

import numpy as np
from recmatch.llm import induced as I
from recmatch.llm import substrings as S


def brute(rows, least):
    data = [(i, (t or "").encode()) for i, t in rows]
    seen = Counter(d[k : k + least] for _, d in data for k in range(len(d) - least + 1))
    out = []
    for i, d in data:
        gone = np.zeros(len(d) + 1, int)
        for k in range(len(d) - least + 1):
            if seen[d[k : k + least]] > 1:
                gone[k] += 1
                gone[k + least] -= 1
        g = np.cumsum(gone)[: len(d)] > 0
        runs = int(g[0]) + int((g[1:] & ~g[:-1]).sum()) if len(g) else 0
        out.append((i, len(d), int(g.sum()), runs, hashlib.sha256(bytes(x for x, y in zip(d, g) if not y)).hexdigest()))
    return sorted(out, key=str)


def test_suffix_order_and_repeats():
    rng = random.Random(10)
    for _ in range(300):
        k = rng.choice([1, 2, 3, 5, 250])
        strings = [bytes(rng.choices(range(k), k=rng.randint(1, rng.choice([5, 30, 80])))) for _ in range(rng.randint(1, 8))]
        strings += [strings[0][: len(strings[0]) // 2 + 1]] * (rng.random() < 0.5)
        t = np.array([x for s in strings for x in [*(b + 1 for b in s), 0]], np.int32)
        ends = np.flatnonzero(t == 0).tolist()
        end = lambda p: ends[bisect.bisect_left(ends, p)]
        want = sorted((p for p in range(len(t)) if t[p]), key=lambda p: (t[p : end(p)].tolist() + [0], end(p)))
        assert I.order_of(t, I.Spill(budget=rng.choice([10, 1 << 30]))).tolist() == want
        most = rng.choice([1, 2, 3, 5, 9])
        seen = Counter(x[i : i + most] for x in strings for i in range(len(x) - most + 1))
        got = I.repeated(strings, most, I.Spill(budget=rng.choice([10, 1000, 1 << 30])))
        assert [g.tolist() for g in got] == [[i + most <= len(x) and seen[x[i : i + most]] > 1 for i in range(len(x))] for x in strings]


def test_runs_are_written_and_read_back(tmp_path):
    from pyarrow import fs

    rng = random.Random(11)
    strings = [bytes(rng.choices(b"abc ", k=300)) for _ in range(40)]
    spill = I.Spill(fs.LocalFileSystem(), str(tmp_path / "runs"), 5000)
    a = I.repeated(strings, 8, spill)
    assert spill.written > 5000 and not list((tmp_path / "runs").iterdir())
    assert all((x == y).all() for x, y in zip(a, I.repeated(strings, 8)))


def test_equals_brute_force(spark):
    rng = random.Random(12)
    words = ["".join(rng.choices("abcdefé ", k=rng.randint(1, 9))) for _ in range(60)]
    base = [" ".join(rng.choices(words, k=rng.randint(1, 60))) for _ in range(30)]
    rows = [(i, "".join(rng.choices(base, k=rng.randint(0, 3)))[rng.randint(0, 9) :]) for i in range(80)]
    rows += [(100, None), (101, ""), (102, "x" * 3000), (103, "x" * 45), (104, rows[0][1]), (105, "ab" * 500), (5, "twin " * 30), (5, "other " * 30), (106, "line\n" * 100)]
    docs = spark.createDataFrame([(i, t, 1, "z") for i, t in rows] + [(None, "null id " * 20, 1, "z"), (106, "line\n" * 100, 2, "y")], "doc_id long, text string, h int, spans string").repartition(4)
    want = brute([*rows, (None, "null id " * 20), (106, "line\n" * 100)], 40)
    for shard, many in ((200, 1000), (1 << 23, 1000), (1 << 23, 2)):
        assert sorted((tuple(r) for r in S.remove_repeats(docs, 40, shard, 4000, many).collect()), key=str) == want
    assert S.remove_repeats(docs.limit(0)).count() == 0


def test_production_settings_spill(tmp_path):
    """A shard of the production size writes runs at the production budget, a few files, and leaves none."""
    from pyarrow import fs

    rng = random.Random(13)
    passage = bytes(rng.choices(range(97, 123), k=450))
    strings = [bytes(rng.choices(range(97, 123), k=200)) + passage[rng.randint(0, 40) :] for _ in range(S.SHARD // 600)]
    spill = I.Spill(fs.LocalFileSystem(), str(tmp_path / "runs"), S.BUDGET)
    flags = I.repeated(strings, 400, spill)
    assert spill.written > 1 << 20 and not list((tmp_path / "runs").iterdir())
    assert all(f.sum() == max(0, len(x) - 200 - 400 + 1) or f.sum() >= 1 for x, f in zip(strings, flags))


def test_a_core_is_sorted_as_a_mark_and_its_number():
    """Windows of 400 bytes round cores of 334 are told apart by 70 symbols, whatever bytes look like a number."""
    rng = random.Random(14)
    cores = [bytes(rng.choices(range(256), k=334)) for _ in range(300)] + [bytes(334), b"\0\0\1" * 111 + b"\0"]
    sides = [bytes(rng.choices(b"\0\1a", k=66)) for _ in range(6)] + [bytes(66), b"\1" * 66]
    bodies, at = [], []
    for _ in range(900):
        p, q = rng.randint(0, 66), rng.randint(0, 66)
        p, q = (p, q) if p + q >= 66 else (66 - p, 66 - q)
        bodies.append(rng.choice(sides)[66 - p :] + rng.choice(cores[-40:]) + rng.choice(sides)[:q])
        at.append(p)
    bodies, at = zip(*dict.fromkeys(zip(bodies, at)))
    short = S.shortened(bodies, at, 334)
    assert 3 * sum(map(len, short)) < sum(map(len, bodies))
    windows = lambda b: [b[k : k + 400] for k in range(len(b) - 399)]
    seen = Counter(x for b, p in zip(bodies, at) for x in zip(windows(b), range(p, -1, -1)))
    flags = I.repeated(short, 67 + S.NUMBER, marks=list(at))
    assert {True, False} == {bool(f.any()) for f in flags}
    for b, p, f in zip(bodies, at, flags):
        assert np.flatnonzero(f).tolist() == [k for k, x in enumerate(windows(b)) if seen[x, p - k] > 1]


def test_table(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    assert sorted((tuple(r) for r in S.remove_repeats(docs).collect()), key=str) == brute([(r.doc_id, r.text) for r in docs.collect()], 400)
