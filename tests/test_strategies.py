"""Invariants of the strategies on hand-made lists, and parity with references."""

import math
import random

import pytest
from recmatch.operators import clustering as G
from recmatch.operators import measures as A
from recmatch.operators import strategies as S
from recmatch.operators.judges import DEFAULT, Judge, NoProbabilities, RemoteJudge, ReplayJudge, black_box
from recmatch.plans.candidates import shared


@pytest.fixture(scope="module")
def lists(spark):
    shared(spark)
    rng = random.Random(1)
    rows = []
    for a in range(1, 13):
        n = a if a < 11 else 10
        truth = rng.randint(0, n)
        for p in range(1, n + 1):
            rows.append((a, a * 100 + p, p, float(n - p), round(rng.choice([0.5, 0.7, 0.9, 0.95]) + rng.random() * 0.05, 6), p == truth))
    return spark.createDataFrame(rows, "anchor_id long, cand_id long, pos int, block_score double, sim double, is_true boolean").cache()


def by_anchor(rows, *cols):
    out = {}
    for r in rows:
        out.setdefault(r.anchor_id, []).append(tuple(r[c] for c in cols))
    return out


def test_scores_are_calibrated(lists):
    for r in S.match_scores(lists, DEFAULT).collect():
        assert (r.score >= 1) == r.yes or r.score == 1
    with pytest.raises(NoProbabilities):
        S.match_scores(lists, black_box(DEFAULT))
    with pytest.raises(NoProbabilities):
        S.compare_scores(lists, black_box(DEFAULT), "probs")
    assert {r.score for r in S.match_scores(lists, black_box(DEFAULT), "label").collect()} <= {0.0, 1.0}


def test_comparison_scores_sum_up(lists):
    for use in ("labels", "probs"):
        for rows in by_anchor(S.compare_scores(lists, DEFAULT, use).collect(), "score").values():
            n = len(rows)
            assert math.isclose(sum(s for (s,) in rows), n * (n - 1), abs_tol=1e-3)


def reference_bubble(items, beats, k):
    items = list(items)
    for t in range(1, min(k, len(items) - 1) + 1):
        for i in range(len(items) - 1, t - 1, -1):
            if beats(items[i], items[i - 1]):
                items[i], items[i - 1] = items[i - 1], items[i]
    return items


@pytest.mark.parametrize("judge", [DEFAULT, Judge("biased", delta=0.05), Judge("noisy", sigma_triple=0.4)], ids=lambda j: j.name)
def test_bubble_equals_sequential_reference(lists, judge):
    asked = {(r.anchor_id, r.a_id, r.b_id): r.label for r in S.compare_triples(lists, judge).collect()}
    source = by_anchor(lists.orderBy("pos").collect(), "cand_id")
    for k in (1, 4, 12):
        got = {r.anchor_id: [c.cand_id for c in r.cands] for r in S.bubble_inrow(lists, judge, k).collect()}
        for a, ids in source.items():
            beats = lambda x, y: asked[a, x, y] == "A" and asked[a, y, x] == "B"  # noqa: E731, B023
            assert got[a] == reference_bubble([i for (i,) in ids], beats, k), (a, k)


def test_rounds_equal_the_fold(lists):
    judge = Judge("noisy", sigma_triple=0.4)
    labels = S.compare_triples(lists, judge).select("anchor_id", "a_id", "b_id", "label").cache()
    ten = lists.filter("anchor_id >= 10")
    got, rounds = S.rank_by_bubble_rounds(ten, lambda q: q.join(labels, ["anchor_id", "a_id", "b_id"]), 4, 10)
    assert rounds == 10 + 4 - 2 and sum(map(len, S.bubble_rounds(10, 4))) * 2 == A.expected("triplewise_topk", 10, 4)[0]
    want = {r.anchor_id: [c.cand_id for c in r.cands] for r in S.bubble_inrow(ten, judge, 4).collect()}
    assert {r.anchor_id: r.order for r in got.collect()} == want


def test_one_wrong_comparison_loses_the_truth_for_bubble_only():
    worth = {"t": 9, "x": 5, "y": 4, "z": 3}
    wrong = lambda a, b: (a, b) == ("x", "t") or ((a, b) != ("t", "x") and worth[a] > worth[b])
    assert reference_bubble(["x", "y", "t", "z"], wrong, 1)[0] == "x"
    score = {a: sum(2 * wrong(a, b) for b in worth if b != a) for a in worth}
    assert sorted(score.values()) == [0, 2, 4, 6] and score["t"] == 4


def test_listwise_and_compound_identities(lists):
    forced, free = by_anchor(S.select(lists, DEFAULT).collect(), "choice", "cand_id"), by_anchor(S.select(lists, DEFAULT, True).collect(), "choice", "cand_id")
    sizes = {a: len(v) for a, v in by_anchor(lists.collect(), "pos").items()}
    assert all(1 <= v[0][0] <= sizes[a] for a, v in forced.items()) and all(0 <= v[0][0] for v in free.values())
    never = Judge("never", theta=-1e9)
    assert by_anchor(S.select(lists, never, True).collect(), "cand_id") == by_anchor(S.select(lists, never).collect(), "cand_id")
    top = by_anchor(S.rank_by_match(lists, DEFAULT, 1).collect(), "cand_id")
    assert by_anchor(S.compound(lists, DEFAULT, DEFAULT, k=1, opt_out=False).collect(), "cand_id") == top
    # One unbiased judge for both stages decides as it does alone.
    assert by_anchor(S.compound(lists, DEFAULT, DEFAULT).collect(), "cand_id") == by_anchor(S.select(lists, DEFAULT, True).collect(), "cand_id")


def test_place_bias_and_what_the_compound_does_to_it(lists):
    full = lists.filter("anchor_id >= 10")
    placed = S.place_at(full)
    for r in placed.groupBy("anchor_id", "slot").agg({"pos": "sum", "cand_id": "count"}).collect():
        assert r["sum(pos)"] == 55 and r["count(cand_id)"] == 10


def test_closed_forms_are_the_published_counts():
    assert A.expected("pairwise", 10) == (10, 20) and A.expected("listwise", 10) == (1, 11)
    assert A.expected("triplewise_topk", 10, 1) == (18, 54) and A.expected("triplewise_topk", 10, 4) == (60, 180)
    assert A.expected("triplewise_allpair", 10) == (90, 270) and A.expected("compound_match", 10, 4) == (11, 25)


def test_log_agrees_with_closed_forms(lists):
    from recmatch.plans.experiments import call_log

    got = {(r.anchor_id, r.strategy): (r.calls, r.records) for r in call_log(lists).groupBy("anchor_id", "strategy").agg({"records": "sum", "model": "count"}).withColumnsRenamed({"sum(records)": "records", "count(model)": "calls"}).collect()}
    for a, rows in by_anchor(lists.collect(), "pos").items():
        n = len(rows)
        for s in A.CLOSED:
            k = min(4, n - 1) if "topk" in s or "bubble" in s else min(4, n)
            want = A.expected(s, n, k)
            if "bubble" in s:
                want = (want[0], want[1] + min(4, n) - k)
            assert got.get((a, s), (0, 0)) == want, (a, s)


def test_greedy_matching_equals_sequential(spark):
    shared(spark)
    rng = random.Random(2)
    edges = [(rng.randint(1, 15), 100 + rng.randint(1, 15), rng.choice([0.5, 0.7, 0.9])) for _ in range(80)]
    edges = list({e[:2]: e for e in edges}.values())
    used, want = set(), set()
    for a, b, w in sorted(edges, key=lambda e: (-e[2], e[0], e[1])):
        if a not in used and b not in used:
            used |= {a, b}
            want.add((a, b, w))
    df = spark.createDataFrame(edges, "src_id long, dst_id long, weight double")
    assert {tuple(r) for r in G.greedy_matching(df).collect()} == want
    got = {r.rid: r.cluster_id for r in G.connected_components(df).collect()}
    assert all(got[a] == got[b] for a, b, _ in edges)


def test_measures_are_safe_where_undefined(spark, lists):
    none = spark.createDataFrame([], "anchor_id long, cand_id long")
    r = A.prf(lists, none).first()
    assert (r.tp, r.fp) == (0, 0) and r.precision is None and r.f1 == 0
    r = A.prf(lists.filter("not is_true"), none).first()
    assert r.f1 is None and r.recall is None


def test_remote_judge_asks_once_and_replays(spark):
    prompts = spark.createDataFrame([(i, f"p{i % 5}") for i in range(40)], "n int, prompt string")

    def transport(batch):
        return [("Yes" if p in ("p1", "p3") else "No", 0.75) for p in batch]

    log = RemoteJudge(transport, in_flight=2, batch=2).log(prompts).cache()
    assert log.count() == 5 and RemoteJudge(transport).log(prompts, log).count() == 0
    replayed = ReplayJudge(log).ask(prompts)
    assert replayed.filter("answer = 'Yes'").count() == 16 and replayed.filter("answer is null").count() == 0


def test_expression_compound_stays_in_the_jvm(lists):
    plan = S.compound(lists, DEFAULT, DEFAULT)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Pandas" not in plan and "CartesianProduct" not in plan
