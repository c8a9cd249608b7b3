"""The three strategies and their compound. All but the remote forms are narrow: a list stays in its row."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from recmatch.operators.judges import Judge, NoProbabilities
from recmatch.plans.blocking import block_tfidf
from recmatch.plans.candidates import nested
from recmatch.plans.workloads import Workload

ORDER = ("pos", "cand_id")
#: Words in a larger share of the labelled records do not make examples alike.
EXAMPLE_DF = 0.5


# Pairwise

def match_pairs(cands: DataFrame, j: Judge) -> DataFrame:
    """Each candidate on its own: p_yes, p_no, yes."""
    p = cands.withColumn("p_yes", F.expr(j.p_yes("spark")))
    return p.withColumn("p_no", F.round(1 - F.col("p_yes"), 6)).withColumn("yes", F.col("p_yes") >= 0.5)


def match_scores(cands: DataFrame, j: Judge, on_missing: str = "raise") -> DataFrame:
    """A calibrated score: yes answers lie at 1 and above, no answers at 1 and below."""
    m = match_pairs(cands, j)
    if j.has_probs:
        return m.withColumn("score", F.round(F.when(F.col("yes"), 1 + F.col("p_yes")).otherwise(1 - F.col("p_no")), 6))
    if on_missing == "raise":
        raise NoProbabilities(j.name)
    return m.withColumn("score", F.col("yes").cast("double"))


def _ranked(scored: DataFrame, k: int | None) -> DataFrame:
    """Rank within each list by score, ties by blocking order; the first k."""
    w = Window.partitionBy("anchor_id").orderBy(F.desc("score"), *ORDER)
    out = scored.withColumn("rank", F.row_number().over(w))
    return out if k is None else out.filter(F.col("rank") <= k)


def rank_by_match(cands: DataFrame, j: Judge, k: int | None = None) -> DataFrame:
    return _ranked(match_scores(cands, j, "label"), k)


def match_best(cands: DataFrame, j: Judge) -> DataFrame:
    """anchor_id, cand_id (null: none): the best-scored candidate, if its answer was yes."""
    best = match_scores(cands, j, "label").groupBy("anchor_id").agg(F.max_by(F.struct("cand_id", "yes"), F.struct("score", -F.col("pos"))).alias("b"))
    return best.select("anchor_id", F.when(F.col("b.yes"), F.col("b.cand_id")).alias("cand_id"))


def match_fewshot(cands: DataFrame, j: Judge, examples: DataFrame) -> DataFrame:
    """Pairs judged with the worked examples of their anchor: the threshold moves to the middle between the like and unlike ones.

    Without examples of both labels it stays. What is added before rounding keeps halves off the border.
    """
    mid = examples.groupBy("anchor_id").agg(F.avg(F.when(F.col("label") == 1, F.col("ex_sim"))).alias("up"), F.avg(F.when(F.col("label") == 0, F.col("ex_sim"))).alias("down"))
    both = cands.join(mid, "anchor_id", "left").withColumn("shift", F.round(F.coalesce((F.col("up") + F.col("down")) / 2 - j.tau, F.lit(0.0)) + 1e-9, 6))
    return both.withColumn("yes", F.expr(j.p_yes("spark", "(sim - shift)")) >= 0.5)


def retrieve_examples(anchors: DataFrame, records: DataFrame, pool: DataFrame, w: Workload, n_pos: int = 3, n_neg: int = 3) -> DataFrame:
    """For each anchor so many labelled pairs of either label whose own anchors are the records most like it, by the token index.

    anchors, records: of the workload's first side. pool: labelled pairs (anchor_id, cand_id, sim, is_true); all are searched.
    The n nearest records with a pair of a label hold the n nearest pairs. anchor_id, label, n, ex_a, ex_c, ex_sim.
    """
    out = None
    for label, n in ((1, n_pos), (0, n_neg)):
        mine = pool.filter(F.col("is_true") == (label == 1)).select(F.col("anchor_id").alias("ex_a"), F.col("cand_id").alias("ex_c"), F.col("sim").alias("ex_sim"))
        near = block_tfidf(anchors, records.join(mine.select(F.col("ex_a").alias("rid")).distinct(), "rid", "left_semi"), replace(w, max_df=EXAMPLE_DF), n)
        best = Window.partitionBy("anchor_id").orderBy("pos", "ex_c")
        one = near.select("anchor_id", F.col("cand_id").alias("ex_a"), "pos").join(mine, "ex_a").withColumn("n", F.row_number().over(best)).filter(F.col("n") <= n)
        one = one.select("anchor_id", F.lit(label).alias("label"), "n", "ex_a", "ex_c", "ex_sim")
        out = one if out is None else out.unionAll(one)
    return out


# Triplewise

def triples(cands: DataFrame) -> DataFrame:
    """All ordered pairs of a list's candidates, made within the row."""
    n = nested(cands)
    x = n.select("anchor_id", "cands", F.explode("cands").alias("x")).select("anchor_id", "x", F.explode("cands").alias("y")).filter("x.pos <> y.pos")
    return x.select("anchor_id", F.col("x.cand_id").alias("a_id"), F.col("y.cand_id").alias("b_id"), F.col("x.sim").alias("a_sim"), F.col("y.sim").alias("b_sim"), F.col("x.pos").alias("a_pos"), F.col("y.pos").alias("b_pos"))


def compare_triples(cands: DataFrame, j: Judge) -> DataFrame:
    p = triples(cands).withColumn("p_a", F.expr(j.p_first("spark", "a_sim", "b_sim", "a_id", "b_id")))
    return p.withColumn("p_b", F.round(1 - F.col("p_a"), 6)).withColumn("label", F.when(F.col("p_a") >= 0.5, "A").otherwise("B"))


def compare_outcomes(asked: DataFrame) -> DataFrame:
    """Both orders of an unordered pair folded: 2 wins, 1 split, 0 losses of the candidate that blocking put first."""
    first = F.col("a_pos") < F.col("b_pos")
    low, high = F.when(first, F.col("a_id")).otherwise(F.col("b_id")), F.when(first, F.col("b_id")).otherwise(F.col("a_id"))
    won = F.when(first, F.col("label") == "A").otherwise(F.col("label") == "B").cast("int")
    return asked.groupBy("anchor_id", low.alias("i_id"), high.alias("j_id")).agg(F.sum(won).cast("int").alias("wins"))


def compare_scores(cands: DataFrame, j: Judge, use: str = "labels") -> DataFrame:
    """A candidate's sum over rivals and both orders, of wins or of probabilities."""
    if use == "probs" and not j.has_probs:
        raise NoProbabilities(j.name)
    asked = compare_triples(cands, j)
    a, b = (F.col("p_a"), F.col("p_b")) if use == "probs" else ((F.col("label") == "A").cast("double"), (F.col("label") == "B").cast("double"))
    both = asked.select("anchor_id", F.col("a_id").alias("cand_id"), a.alias("v")).unionAll(asked.select("anchor_id", F.col("b_id").alias("cand_id"), b.alias("v")))
    s = both.groupBy("anchor_id", "cand_id").agg(F.round(F.sum("v"), 6).alias("score"))
    return cands.join(s, ["anchor_id", "cand_id"], "left").na.fill(0.0, ["score"])


def rank_by_allpair(cands: DataFrame, j: Judge, k: int | None = None, use: str = "labels") -> DataFrame:
    return _ranked(compare_scores(cands, j, use), k)


def bubble_inrow(cands: DataFrame, j: Judge, k: int, weigh: str | None = None) -> DataFrame:
    """k partial bubble passes within the row, from the tail to the head; only a win in both orders swaps.

    anchor_id, cands in their final order. weigh: a long column of cands; adds spent, its sum over what all questions show.
    """
    n = nested(cands, *([weigh] if weigh else []))
    digest = lambda text: F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / 4294967296 - 0.5
    if j.sigma_record:
        key = lambda e: F.concat(F.lit(f"{j.seed}|r|"), F.col("anchor_id").cast("string"), F.lit("|"), e["cand_id"].cast("string"))
        n = n.withColumn("cands", F.transform("cands", lambda e: e.withField("read", e["sim"] + j.sigma_record * digest(key(e)))))
    seen = "read" if j.sigma_record else "sim"
    size = F.size("cands")
    steps = F.flatten(F.transform(F.sequence(F.lit(1), F.least(F.lit(k), size)), lambda t: F.when(size > t, F.reverse(F.sequence(t, size - 1))).otherwise(F.array().cast("array<int>"))))

    def beats(x: Column, y: Column) -> Column:
        """x, the later one, against y, asked in both orders."""
        d, up = x[seen] - y[seen], F.lit(j.delta)
        if not j.sigma_triple:
            logit = lambda v: F.round(1 / (1 + F.exp(-j.beta * v)), 6)
            return (logit(d + up) >= 0.5) & (logit(up - d) < 0.5)
        noise = lambda p, q: j.sigma_triple * digest(F.concat(F.lit(f"{j.seed}|t|"), F.col("anchor_id").cast("string"), F.lit("|"), p["cand_id"].cast("string"), F.lit("|"), q["cand_id"].cast("string")))
        logit = lambda v: F.round(1 / (1 + F.exp(-j.beta * v)), 6)
        return (logit(d + noise(x, y) + up) >= 0.5) & (logit(-d + noise(y, x) + up) < 0.5)

    def step(acc: Column, i: Column) -> Column:
        x, y = F.element_at(acc, i + 1), F.element_at(acc, i)
        swapped = F.transform(acc, lambda e, p: F.when(p == i - 1, x).when(p == i, y).otherwise(e))
        return F.when(beats(x, y), swapped).otherwise(acc)

    if weigh:
        shown = lambda c, i: 2 * (F.element_at(c, i)[weigh] + F.element_at(c, i + 1)[weigh])  # noqa: E731  asked in both orders
        start = F.struct(F.col("cands").alias("c"), F.lit(0).cast("long").alias("spent"))
        fold = F.aggregate(steps, start, lambda acc, i: F.struct(step(acc["c"], i).alias("c"), (acc["spent"] + shown(acc["c"], i)).alias("spent")))
        return n.withColumn("f", fold).select("anchor_id", F.col("f.c").alias("cands"), F.col("f.spent").alias("spent"))
    return n.withColumn("cands", F.aggregate(steps, F.col("cands"), step))


def rank_by_bubble(cands: DataFrame, j: Judge, k: int) -> DataFrame:
    """The first k after k passes: anchor_id, cand_id, rank, pos, sim, is_true."""
    out = bubble_inrow(cands, j, k).select("anchor_id", F.posexplode(F.slice("cands", 1, k)).alias("r", "c"))
    return out.select("anchor_id", F.col("c.cand_id").alias("cand_id"), (F.col("r") + 1).alias("rank"), F.col("c.pos").alias("pos"), F.col("c.sim").alias("sim"), F.col("c.is_true").alias("is_true"))


def compare_identify(cands: DataFrame, j_cmp: Judge, j_match: Judge) -> DataFrame:
    """The winner of one bubble pass, if the pairwise question accepts it."""
    top = rank_by_bubble(cands, j_cmp, 1)
    return top.select("anchor_id", F.when(F.expr(j_match.p_yes("spark")) >= 0.5, F.col("cand_id")).alias("cand_id"))


def order_flip_rate(asked: DataFrame) -> DataFrame:
    o = compare_outcomes(asked)
    return o.agg(F.count(F.lit(1)).alias("pairs"), F.sum((F.col("wins") == 1).cast("long")).alias("flips"), F.round(F.avg((F.col("wins") == 1).cast("double")), 6).alias("flip_rate"))


def bubble_rounds(n: int, k: int) -> list[list[tuple[int, int]]]:
    """The comparisons (pass, slot) of k partial passes over n slots, in synchronous rounds.

    Pass t starts two comparisons behind pass t - 1, which is when its first slot pair is settled; a remote judge
    then gets one batch of all anchors a round: n + k - 2 rounds instead of k (2n - k - 1) / 2.
    """
    rounds: dict[int, list[tuple[int, int]]] = {}
    for t in range(1, min(k, n - 1) + 1):
        for step, slot in enumerate(range(n - 1, t - 1, -1)):
            rounds.setdefault(step + 2 * (t - 1), []).append((t, slot))
    return [rounds[r] for r in sorted(rounds)]


# Listwise

def select(cands: DataFrame, j: Judge, opt_out: bool = False, by: tuple[str, ...] = ("anchor_id",)) -> DataFrame:
    """anchor_id, choice (0: none), cand_id: one question a list. by: what tells lists apart, if an anchor has several."""
    w = cands.withColumn("worth", F.expr(j.worth("spark"))).withColumn("held", F.expr(j.held("spark")))
    best = w.groupBy(*by).agg(F.max_by(F.struct("pos", "cand_id"), F.struct("worth", -F.col("pos"))).alias("b"), F.max("held").alias("most"))
    keep = F.col("most") >= j.least if opt_out else F.lit(True)
    return best.select(*by, F.when(keep, F.col("b.pos")).otherwise(F.lit(0)).cast("int").alias("choice"), F.when(keep, F.col("b.cand_id")).alias("cand_id"))


def select_then_verify(cands: DataFrame, j_sel: Judge, j_match: Judge) -> DataFrame:
    picked = select(cands, j_sel).select("anchor_id", "cand_id").join(cands, ["anchor_id", "cand_id"])
    return picked.select("anchor_id", F.when(F.expr(j_match.p_yes("spark")) >= 0.5, F.col("cand_id")).alias("cand_id"))


def place_at(cands: DataFrame, n: int = 10) -> DataFrame:
    """Lists of n that hold their true candidate, once for each slot it is moved to; pos is the new one, slot the true one's."""
    size = Window.partitionBy("anchor_id")
    full = cands.withColumn("size", F.count(F.lit(1)).over(size)).withColumn("has", F.sum(F.col("is_true").cast("int")).over(size)).filter((F.col("size") == n) & (F.col("has") == 1))
    true_pos = F.max(F.when(F.col("is_true"), F.col("pos"))).over(size)
    rest = F.col("pos") - F.when(F.col("pos") > F.col("true_pos"), 1).otherwise(0)
    out = full.withColumn("true_pos", true_pos).withColumn("slot", F.explode(F.sequence(F.lit(1), F.lit(n))))
    return out.withColumn("pos", F.when(F.col("is_true"), F.col("slot")).otherwise(rest + F.when(rest >= F.col("slot"), 1).otherwise(0)).cast("int")).drop("size", "has", "true_pos")


def fit_context(cands: DataFrame, tokens: Column, budget: int) -> DataFrame:
    """The longest head of each list whose records fit a token budget."""
    run = F.sum(tokens).over(Window.partitionBy("anchor_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0))
    return cands.withColumn("used", run).filter(F.col("used") <= budget)


# Compound

def shortlist(cands: DataFrame, ranker: str, j: Judge, k: int) -> DataFrame:
    """The k first by a ranker, with new positions; columns as cands has them."""
    if ranker == "match":
        ranked = rank_by_match(cands, j, k)
    elif ranker == "allpair":
        ranked = rank_by_allpair(cands, j, k)
    elif ranker == "bubble":
        ranked = rank_by_bubble(cands, j, k)
    elif ranker == "block":
        ranked = cands.withColumn("rank", F.col("pos")).filter(F.col("rank") <= k)
    else:
        raise ValueError(ranker)
    return ranked.select("anchor_id", "cand_id", F.col("rank").cast("int").alias("pos"), "sim", "is_true")


def compound(cands: DataFrame, j_rank: Judge, j_select: Judge, ranker: str = "match", k: int = 4, opt_out: bool = True) -> DataFrame:
    return select(shortlist(cands, ranker, j_rank, k), j_select, opt_out)


# Remote bubble

def rank_by_bubble_rounds(cands: DataFrame, ask, k: int, n: int) -> tuple[DataFrame, int]:
    """The bubble ranking by synchronous rounds for a judge that is asked in batches.

    ask: a function of a DataFrame (anchor_id, a_id, b_id) that adds label ('A' or 'B'); one batch a round holds both
    orders of all lists' comparisons of that round. Returns (anchor_id, order: candidate ids, best first), and the rounds.
    """
    state = nested(cands).select("anchor_id", F.col("cands.cand_id").alias("order"))
    rounds = bubble_rounds(n, k)
    for r in rounds:
        slots = F.array(*(F.lit(s) for _, s in r))
        asked = state.select("anchor_id", F.explode(slots).alias("slot"), "order").filter(F.col("slot") < F.size("order"))
        pairs = asked.select("anchor_id", "slot", F.element_at("order", F.col("slot") + 1).alias("x"), F.element_at("order", F.col("slot")).alias("y"))
        both = pairs.select("anchor_id", "slot", F.col("x").alias("a_id"), F.col("y").alias("b_id"), F.lit(True).alias("later_first")).unionAll(pairs.select("anchor_id", "slot", F.col("y").alias("a_id"), F.col("x").alias("b_id"), F.lit(False).alias("later_first")))
        won = F.when(F.col("later_first"), F.col("label") == "A").otherwise(F.col("label") == "B")
        swap = ask(both).groupBy("anchor_id", "slot").agg(F.min(won).alias("swap")).filter("swap").groupBy("anchor_id").agg(F.collect_set("slot").alias("swaps"))
        at = lambda p: F.element_at("order", p)
        moved = F.transform("order", lambda e, p: F.when(F.array_contains("swaps", p), at(p)).when(F.array_contains("swaps", p + 1), at(p + 2)).otherwise(e))
        state = state.join(swap, "anchor_id", "left").select("anchor_id", F.when(F.col("swaps").isNull(), F.col("order")).otherwise(moved).alias("order")).checkpoint()
    return state, len(rounds)
