"""Costs and the experiments on the workloads. Judges are synthetic: only counts, ratios and orderings mean anything."""

from __future__ import annotations

import gc

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from recmatch.functions import prompts as P
from recmatch.functions.prompts import count_tokens
from recmatch.operators import baselines as BL
from recmatch.operators import measures as A
from recmatch.operators import strategies as S
from recmatch.operators.judges import LADDER, LENIENT, NEWER, OLDER, RANKER, Judge
from recmatch.plans import methods as M
from recmatch.plans.blocking import block_tfidf
from recmatch.plans.candidates import candidates, compared, derive_sql, each, kept, sample, side, truth
from recmatch.plans.methods import PLACED, W, on, query
from recmatch.plans.workloads import WORKLOADS, Workload
from recmatch.sources.tables import table

#: Prices are invented: dollars for a thousand input tokens, and for an hour of a rented accelerator.
PRICES = {"strong": 0.0030, "cheap": 0.0002}
GPU_HOUR = 1.20
#: Words of an answer: a label or a number.
ANSWER = 1
ALL = tuple(f"w{i}" for i in range(1, 9))

_lists_sql = "(select anchor_id, count(*) as n from cs group by anchor_id)"


def call_log(cands: DataFrame, k: int = 4) -> DataFrame:
    """One row a call that a strategy makes: strategy, stage, model, anchor_id, records. Made from the lists, not from the closed forms."""
    c = cands.select("anchor_id", "cand_id", "pos")
    size = c.groupBy("anchor_id").agg(F.count(F.lit(1)).alias("n"))
    row = lambda df, s, stage, model, records: df.select(F.lit(s).alias("strategy"), F.lit(stage).alias("stage"), F.lit(model).alias("model"), "anchor_id", F.lit(records).cast("long").alias("records") if isinstance(records, int) else records.cast("long").alias("records"))
    twice = size.filter("n > 1").select("anchor_id", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n") * (F.col("n") - 1))).alias("q"))
    bubble = lambda k: size.select("anchor_id", "n", F.explode(F.sequence(F.lit(1), F.least(F.lit(k).cast("long"), F.col("n") - 1))).alias("t")).filter("n > 1").select("anchor_id", F.explode(F.sequence(F.lit(1).cast("long"), 2 * (F.col("n") - F.col("t")))).alias("q"))
    kept = F.least(F.lit(k).cast("long"), F.col("n")) + 1
    parts = [
        row(c, "pairwise", "decide", "strong", 2), row(c, "pairwise_fewshot", "decide", "strong", 14),
        row(bubble(k), "triplewise_topk", "rank", "strong", 3),
        row(bubble(1), "triplewise_identify", "rank", "strong", 3), row(size, "triplewise_identify", "check", "strong", 2),
        row(twice, "triplewise_allpair", "rank", "strong", 3),
        row(size, "listwise", "decide", "strong", F.col("n") + 1),
        row(size, "listwise_verify", "decide", "strong", F.col("n") + 1), row(size, "listwise_verify", "check", "strong", 2),
        row(c, "compound_match", "rank", "cheap", 2), row(size, "compound_match", "decide", "strong", kept),
        row(bubble(k), "compound_bubble", "rank", "cheap", 3), row(size, "compound_bubble", "decide", "strong", kept),
        row(twice, "compound_allpair", "rank", "cheap", 3), row(size, "compound_allpair", "decide", "strong", kept),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    return out


def closed_sql(what: int) -> str:
    """The closed forms over the lists, as SQL."""
    bubble = lambda f: f.replace("k * (2 * n - k - 1)", "k0 * (2 * n - k0 - 1)")  # noqa: E731  a list of n has n - 1 passes at most
    return " union all ".join(f"select '{s}' as strategy, cast(sum({bubble(f[what])}) as bigint) as v from (select n, least(4, n - 1) as k0, least(4, n) as k from {_lists_sql} l) z" for s, f in A.CLOSED.items())


def _counted(s, d, column) -> DataFrame:
    log = call_log(candidates(s, d, W))
    v = F.count(F.lit(1)) if column == "calls" else F.sum("records")
    return log.groupBy("strategy").agg(v.alias("v"))


@query("cost_calls", on(W, f"select * from ({closed_sql(0)}) q"))
def _(s, d):
    return _counted(s, d, "calls")


@query("cost_records", on(W, f"select * from ({closed_sql(1)}) q"))
def _(s, d):
    return _counted(s, d, "records")


@query("cost_closed_forms", "select strategy, cast(n as integer) as n, cast(k as integer) as k, cast(calls as bigint) as calls, cast(records as bigint) as records from (with sizes as (select distinct n, unnest(range(1, n + 1)) as k from (select count(*) as n from lineitem group by l_orderkey) l) " + " union all ".join(f"select '{s}' as strategy, n, k, {c} as calls, {r} as records from sizes" for s, (c, r) in A.CLOSED.items()) + ") q")
def closed_forms(s, d):
    """For every length that the orders' lists of lines have."""
    sizes = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).cast("int").alias("n")).select("n").distinct()
    nk = kept(s, (d, "lines", "sizes"), lambda: sizes).withColumn("k", F.explode(F.sequence(F.lit(1), F.col("n"))))
    out = None
    for name, (c, r) in A.CLOSED.items():
        part = nk.select(F.lit(name).alias("strategy"), "n", "k", F.expr(c).cast("long").alias("calls"), F.expr(r).cast("long").alias("records"))
        out = part if out is None else out.unionAll(part)
    return out


def with_words(s, d, key: str) -> DataFrame:
    """The candidate table with ta and tb, the words of either record in a prompt, and tf, those of its anchor's examples."""
    return kept(s, (d, key, "words"), lambda: _with_words(s, d, key))


def _with_words(s, d, key: str) -> DataFrame:
    words = lambda which, rid, name: M.record_words(s, d, key, which).select(F.col("rid").alias(rid), F.col("words").alias(name))
    shown = M.examples(s, d, key).join(words("d1", "ex_a", "wa"), "ex_a").join(words("d2", "ex_c", "wb"), "ex_c")
    tf = shown.groupBy("anchor_id").agg(F.sum(F.col("wa") + F.col("wb") + P.EXAMPLE_WORDS).alias("tf"))
    c = candidates(s, d, key).select("anchor_id", "cand_id", "pos", "sim", "is_true")
    return c.join(words("d1", "anchor_id", "ta"), "anchor_id").join(words("d2", "cand_id", "tb"), "cand_id").join(tf, "anchor_id", "left").na.fill(0, ["tf"])


def spent(c: DataFrame, j, ranker, k: int = 4) -> DataFrame:
    """strategy, model, calls, in_tokens, out_tokens of all strategies over lists with words (with_words): what the rendered
    questions hold. Which records a bubble compares, and which are kept, follow from the judges' own answers."""
    pair = P.PAIR_WORDS + F.col("ta") + F.col("tb")
    size = c.groupBy("anchor_id").agg(F.count(F.lit(1)).alias("n"), F.max("ta").alias("ta"), F.sum("tb").alias("tb"))
    whole = P.LIST_WORDS + F.col("ta") + F.col("tb") + F.col("n")
    row = lambda df, strategy, model, tokens, calls=F.lit(1): df.select(F.lit(strategy).alias("strategy"), F.lit(model).alias("model"), calls.cast("long").alias("calls"), tokens.cast("long").alias("tokens"))
    picked = lambda one: one.select("anchor_id", "cand_id").join(c, ["anchor_id", "cand_id"])

    def bubble(k: int, judge) -> DataFrame:
        asked = F.least(F.lit(k), F.col("n") - 1)
        out = S.bubble_inrow(c, judge, k, "tb").select("anchor_id", "spent").join(size.select("anchor_id", "n", "ta"), "anchor_id")
        return out.withColumn("asked", asked * (2 * F.col("n") - asked - 1)).withColumn("tokens", F.col("asked") * (P.TRIPLE_WORDS + F.col("ta")) + F.col("spent"))

    def short(how: str) -> DataFrame:
        return picked(S.shortlist(c, how, ranker, k)).groupBy("anchor_id").agg(F.count(F.lit(1)).alias("n"), F.max("ta").alias("ta"), F.sum("tb").alias("tb"))

    rivals = F.col("n") * (F.col("n") - 1) * (P.TRIPLE_WORDS + F.col("ta")) + 2 * (F.col("n") - 1) * F.col("tb")
    twice = F.col("n") * (F.col("n") - 1)
    top, one, cheap = bubble(k, j), bubble(1, j), bubble(k, ranker)
    parts = [
        row(c, "pairwise", "strong", pair), row(c, "pairwise_fewshot", "strong", pair + F.col("tf")),
        row(top, "triplewise_topk", "strong", F.col("tokens"), F.col("asked")),
        row(one, "triplewise_identify", "strong", F.col("tokens"), F.col("asked")), row(picked(S.rank_by_bubble(c, j, 1)), "triplewise_identify", "strong", pair),
        row(size, "triplewise_allpair", "strong", rivals, twice),
        row(size, "listwise", "strong", whole + P.NONE_WORDS),
        row(size, "listwise_verify", "strong", whole), row(picked(S.select(c, j)), "listwise_verify", "strong", pair),
        row(c, "compound_match", "cheap", pair), row(short("match"), "compound_match", "strong", whole + P.NONE_WORDS),
        row(cheap, "compound_bubble", "cheap", F.col("tokens"), F.col("asked")), row(short("bubble"), "compound_bubble", "strong", whole + P.NONE_WORDS),
        row(size, "compound_allpair", "cheap", rivals, twice), row(short("allpair"), "compound_allpair", "strong", whole + P.NONE_WORDS),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    return out.groupBy("strategy", "model").agg(F.sum("calls").alias("calls"), F.sum("tokens").alias("in_tokens"), (F.sum("calls") * ANSWER).alias("out_tokens"))


def spent_sql(key: str, j, ranker, k: int = 4) -> str:
    """After derive_sql: common table expressions ending in ledger, the counterpart of spent(), for judges that compare without noise."""
    a, b = M.words_sql(key, "d1"), M.words_sql(key, "d2")
    pair, whole = f"{P.PAIR_WORDS} + ta + tb", f"{P.LIST_WORDS} + ta + tb + n"
    plan = ", ".join(f"({n}, {kk}, {i}, {slot})" for n in range(2, 11) for kk in (1, k) for i, slot in enumerate((x for t in range(1, min(kk, n - 1) + 1) for x in range(n - 1, t - 1, -1)), 1))
    asked = lambda strategy, model, kk: f"select '{strategy}' as strategy, '{model}' as model, 2 * steps as calls, 2 * steps * ({P.TRIPLE_WORDS} + ta) + shown as tokens from bubbled join li using (anchor_id) where kk = {kk}"
    row = lambda strategy, model, tokens, src, calls="1": f"select '{strategy}', '{model}', {calls}, {tokens} from {src}"
    picked = lambda src: f"(select lt.* from lt join {src} p0 using (anchor_id, cand_id)) p1"
    kept = lambda how: f"(select anchor_id, count(*) as n, max(ta) as ta, sum(tb) as tb from {picked(M.short_sql(how, ranker, k))} group by anchor_id) p2"
    rivals, twice = f"n * (n - 1) * ({P.TRIPLE_WORDS} + ta) + 2 * (n - 1) * tb", "n * (n - 1)"
    parts = [
        asked("triplewise_topk", "strong", k), asked("triplewise_identify", "strong", 1), asked("compound_bubble", "cheap", k),
        row("pairwise", "strong", pair, "lt"), row("pairwise_fewshot", "strong", f"{pair} + tf", "lt"), row("triplewise_identify", "strong", pair, picked(M.bubble_sql(1))),
        row("triplewise_allpair", "strong", rivals, "li", twice), row("listwise", "strong", f"{whole} + {P.NONE_WORDS}", "li"),
        row("listwise_verify", "strong", whole, "li"), row("listwise_verify", "strong", pair, picked(M.s_sql(j, False))),
        row("compound_match", "cheap", pair, "lt"), row("compound_allpair", "cheap", rivals, "li", twice),
        *(row(f"compound_{how}", "strong", f"{whole} + {P.NONE_WORDS}", kept(how)) for how in ("match", "bubble", "allpair")),
    ]
    return f"""{M.examples_sql(key)}, fw as (select anchor_id, cast(sum(x.words + y.words + {P.EXAMPLE_WORDS}) as bigint) as tf from ex join {a} x on x.rid = ex_a join {b} y on y.rid = ex_c group by anchor_id),
 lt as (select cs.*, x.words as ta, y.words as tb, coalesce(tf, 0) as tf from cs join {a} x on x.rid = cs.anchor_id join {b} y on y.rid = cs.cand_id left join fw using (anchor_id)),
 li as (select anchor_id, count(*) as n, max(ta) as ta, sum(tb) as tb from lt group by anchor_id),
 bubbled as (with recursive sched(n, kk, step, slot) as (values {plan}),
  z as (select anchor_id, count(*) as n, kk, list(struct_pack(sim := sim, tb := tb) order by pos) as o, 0 as step, cast(0 as bigint) as shown from lt, (values (1), ({k})) v(kk) group by anchor_id, kk
  union all select anchor_id, z.n, z.kk, case when o[slot + 1].sim > o[slot].sim then list_concat(o[1:slot - 1], [o[slot + 1], o[slot]], o[slot + 2:]) else o end, z.step + 1, shown + 2 * (o[slot].tb + o[slot + 1].tb)
   from z join sched on sched.n = z.n and sched.kk = z.kk and sched.step = z.step + 1)
  select anchor_id, kk, max(step) as steps, max(shown) as shown from z group by anchor_id, kk),
 ledger as (select strategy, model, cast(sum(calls) as bigint) as calls, cast(sum(tokens) as bigint) as in_tokens, cast(sum(calls) * {ANSWER} as bigint) as out_tokens from ({' union all '.join(parts)}) l0 group by strategy, model),
 usd as (select strategy, round(sum((in_tokens + out_tokens) / 1000e0 * case model {' '.join(f"when '{m}' then {p}e0" for m, p in PRICES.items())} end), 6) as usd from ledger group by strategy) """


_ledger_sql = spent_sql(W, LENIENT, RANKER)
_ratio_sql = "(select strategy, round(usd / (select usd from usd where strategy = 'pairwise'), 6) as ratio from usd)"
_front_sql = M.by_strategy_sql(W, [LENIENT])


@query("cost_tokens", on(W, _ledger_sql + "select * from ledger"))
def ledger(s, d):
    return spent(with_words(s, d, W), LENIENT, RANKER)


def usd(s, log: DataFrame) -> DataFrame:
    book = s.createDataFrame([(m, p) for m, p in PRICES.items()], "model string, usd_per_1k double")
    return log.join(F.broadcast(book), "model").withColumn("usd", (F.col("in_tokens") + F.col("out_tokens")) / 1000 * F.col("usd_per_1k")).groupBy("strategy").agg(F.round(F.sum("usd"), 6).alias("usd"))


@query("cost_usd", on(W, _ledger_sql + "select * from usd"))
def dollars(s, d):
    return usd(s, ledger(s, d))


@query("cost_gpu", f"select user_id, round(cast(date_sub('second', min(ts), max(ts)) as double) * {GPU_HOUR}e0 / 3600, 6) as usd from events group by user_id")
def _(s, d):
    """An accelerator rented from a user's first event to the last."""
    seconds = F.expr("timestampdiff(second, min(ts), max(ts))").cast("double")
    return table(s, d, "events").groupBy("user_id").agg(F.round(seconds * GPU_HOUR / 3600, 6).alias("usd"))


def ratios(c: DataFrame) -> DataFrame:
    """Dollars against the pairwise strategy's."""
    return c.join(F.broadcast(c.filter("strategy = 'pairwise'").select(F.col("usd").alias("base")))).select("strategy", "usd", F.round(F.col("usd") / F.col("base"), 6).alias("ratio"))  # one row


@query("cost_ratio", on(W, _ledger_sql + f"select * from {_ratio_sql} q"))
def ratio(s, d):
    return ratios(dollars(s, d)).select("strategy", "ratio")


_priced = {"triplewise": "triplewise_identify", "compound": "compound_match"}
_f1_sql = f", fs as ({_front_sql}), fu as (select case strategy {' '.join(f"when '{a}' then '{b}'" for a, b in _priced.items())} else strategy end as strategy, f1 from fs), fc as (select strategy, f1, usd from fu join usd using (strategy)) "


@query("cost_frontier", on(W, _ledger_sql + _f1_sql + "select * from fc x where not exists (select 1 from fc y where y.usd <= x.usd and y.f1 >= x.f1 and (y.usd < x.usd or y.f1 > x.f1))"))
def frontier(s, d):
    f1 = M.by_strategy(s, d, [W], [LENIENT]).replace(_priced, subset=["strategy"]).select("strategy", "f1")
    return A.pareto(f1.join(dollars(s, d), "strategy"), "usd", "f1").select("strategy", "f1", "usd")


# --- Experiments

@query("exp_main_table", M.across_sql(ALL, [OLDER, NEWER]))
def main_table(s, d):
    return each(s, d, ALL, lambda k: M.by_strategy(s, d, [k], [OLDER, NEWER]))


@query("exp_main_table_w2", on("w2", M.by_strategy_sql("w2", [NEWER])))
def _(s, d):
    return M.by_strategy(s, d, ["w2"], [NEWER])


for _key in ("w1", "w5", "w6", "w7", "w8"):
    query(f"exp_main_table_{_key}", on(_key, M.by_strategy_sql(_key, [LENIENT])))(lambda s, d, key=_key: M.by_strategy(s, d, [key], [LENIENT]))

_stats_sql = " union all ".join(
    f"select * from ({derive_sql(k).split(' idx as (')[0].rstrip().rstrip(',')} select '{k}' as workload, (select count(*) from d1) as d1, (select count(*) from d2) as d2, cast({len(WORKLOADS[k].attributes)} as integer) as attributes, (select count(*) from truth where anchor_id in (select rid from d1) and cand_id in (select rid from d2)) as positives) s{i}"
    for i, k in enumerate(ALL)
)


@query("exp_dataset_stats", _stats_sql)
def stats(s, d):
    """A workload at a time, one row each: no plan holds the shuffles of all until its end."""
    rows = []
    for k in ALL:
        rows.append((k, *sizes(side(s, d, WORKLOADS[k], "d1"), side(s, d, WORKLOADS[k], "d2"), truth(s, d, k)), len(WORKLOADS[k].attributes)))
        gc.collect()
        s.sparkContext._jvm.System.gc()  # Spark deletes the shuffles that nobody can read
    return s.createDataFrame(rows, "workload string, d1 long, d2 long, positives long, attributes int").select("workload", "d1", "d2", "attributes", "positives")


def sizes(d1: DataFrame, d2: DataFrame, true: DataFrame) -> tuple[int, int, int]:
    """Rows of both sides, and the pairs of the truth with both ends there. The second side is read once, its ids alone are dealt."""

    good = true.join(d1.select(F.col("rid").alias("anchor_id")), "anchor_id", "left_semi")
    n1 = d1.count()
    both = d2.select("rid", F.lit(1).alias("n"), F.lit(0).alias("m")).unionAll(good.select("cand_id", F.lit(0), F.lit(1)))
    met = both.groupBy("rid").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))
    n2, positives = met.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.when((F.col("n") > 0) & F.col("rid").isNotNull(), F.col("m"))), F.lit(0))).first()
    return n1, n2, positives


@query("exp_blocking", " union all ".join(f"select * from ({derive_sql(k)}{M._recall_sql.replace('select cast(k as', f'select {chr(39)}{k}{chr(39)} as workload, cast(k as')}) b{i}" for i, k in enumerate(ALL)))
def _(s, d):
    return each(s, d, ALL, lambda key: M.blocking_recall(s, d, key).select(F.lit(key).alias("workload"), "k", "anchors", "recall"))


@query("exp_sampling", on(W, "select rid, rid in (select anchor_id from truth) as is_matched from picked"))
def _(s, d):
    return sample(side(s, d, WORKLOADS[W], "d1"), truth(s, d, W))


def fewshot_rates(s, d, keys, judges) -> DataFrame:
    """Pairwise without and with examples beside listwise, workload by workload."""

    def rates(key):
        out, c, ex = None, candidates(s, d, key), M.examples(s, d, key)
        for j in judges:
            jj = j.with_tau(min(j.tau, WORKLOADS[key].tau))
            few = S.match_fewshot(c, jj, ex).filter("yes").select("anchor_id", "cand_id")
            for n, dec in (("pairwise", M.decide(c, "pairwise", jj)), ("pairwise_fewshot", few), ("listwise", M.decide(c, "listwise", jj))):
                one = A.prf(c, dec).select(F.lit(key).alias("workload"), F.lit(j.name).alias("judge"), F.lit(n).alias("strategy"), "tp", "fp", "fn", "precision", "recall", "f1")
                out = one if out is None else out.unionAll(one)
        return out

    return each(s, d, keys, rates)


def fewshot_rates_sql(keys, judges) -> str:
    def one(key, j):
        jj = j.with_tau(min(j.tau, WORKLOADS[key].tau))
        decisions = (("pairwise", M.yes_sql(jj)), ("pairwise_fewshot", f"(select anchor_id, cand_id from {M.fewshot_sql(jj)} y0 where yes)"), ("listwise", M.s_sql(jj, True)))
        return " union all ".join(M.prf_sql(dec, f"'{key}' as workload, '{j.name}' as judge, '{n}' as strategy, ") for n, dec in decisions)

    return " union all ".join(f"select * from ({derive_sql(k)}{M.examples_sql(k)}{' union all '.join(one(k, j) for j in judges)}) w{i}" for i, k in enumerate(keys))


@query("exp_fewshot", fewshot_rates_sql(ALL, [OLDER, NEWER]))
def fewshot(s, d):
    return fewshot_rates(s, d, ALL, [OLDER, NEWER])


@query("exp_compound_vs_single", on("w8", M.by_strategy_sql("w8", [OLDER])))
def _(s, d):
    return M.by_strategy(s, d, ["w8"], [OLDER])


@query("exp_cost", on(W, _ledger_sql + f"select * from usd join {_ratio_sql} r using (strategy)"))
def _(s, d):
    return ratios(dollars(s, d))


#: Compares with a liking for what comes first, and errs.
SHY = Judge("place-shy", tau=0.8, delta=0.04, sigma_triple=0.3, seed=14)


def position_f1(cands: DataFrame, choose) -> DataFrame:
    """slot, lists, hits, wrong, f1 of a choice on lists with the true candidate in each slot."""
    p = S.place_at(cands).withColumn("anchor_id", F.col("anchor_id") * 100 + F.col("slot"))
    got = choose(p).select("anchor_id", F.col("cand_id").alias("got"))
    by = p.filter("is_true").select("anchor_id", "slot", "cand_id").join(got, "anchor_id").groupBy("slot").agg(F.count(F.lit(1)).alias("lists"), F.count_if(F.col("got") == F.col("cand_id")).alias("hits"), F.count_if(F.col("got") != F.col("cand_id")).alias("wrong"))
    return by.withColumn("f1", F.round(200.0 * F.col("hits") / (F.col("hits") + F.col("wrong") + F.col("lists")), 4))


_placed = "(select anchor_id * 100 + slot as anchor_id, cand_id, pos, sim, is_true, slot from placed)"
_curves = {"listwise": M.s_sql(PLACED, True, _placed), "compound": M._compound_on(_placed), "unbiased": M.s_sql(LENIENT, True, _placed), "triplewise": M.identify_sql(SHY, SHY).replace("from cs", f"from (select anchor_id, cand_id, pos, sim from {_placed} p0) p00")}


@query("exp_position", on(W, M._placed_sql + "select method, slot, lists, hits, wrong, round(200.0e0 * hits / (hits + wrong + lists), 4) as f1 from (" + " union all ".join(f"select '{n}' as method, p.slot, count(*) as lists, count(*) filter (c.cand_id = p.cand_id) as hits, count(*) filter (c.cand_id <> p.cand_id) as wrong from {_placed} p join {dec} c using (anchor_id) where p.is_true group by p.slot" for n, dec in _curves.items()) + ") z"))
def _(s, d):
    c = candidates(s, d, W)
    ways = {"listwise": lambda p: S.select(p, PLACED, True), "compound": lambda p: S.compound(p, PLACED, PLACED), "unbiased": lambda p: S.select(p, LENIENT, True), "triplewise": lambda p: S.compare_identify(p, SHY, SHY)}
    out = None
    for n, way in ways.items():
        one = position_f1(c, way).withColumn("method", F.lit(n))
        out = one if out is None else out.unionByName(one)
    return out


@query("exp_judges", on(W, M.by_strategy_sql(W, LADDER)))
def _(s, d):
    return M.by_strategy(s, d, [W], LADDER)


@query("exp_rank_recall", on(W, " union all ".join(f"select '{j.name}' as judge, '{n}' as ranker, count(*) as lists, round(avg(case when rank <= 1 then 1.0e0 else 0 end), 6) as recall from (select anchor_id, min(rank) as rank from {M.ranked_sql(src)} q where is_true group by anchor_id) t" for j in LADDER for n, src in (("pairwise", M.m_sql(j)), ("allpair", M.c_sql(j))))))
def rank_recall(s, d):
    c = candidates(s, d, W)
    out = None
    for j in LADDER:
        for n, ranked in (("pairwise", S.rank_by_match(c, j)), ("allpair", S.rank_by_allpair(c, j))):
            one = A.ranking_recall(ranked, (1,)).select(F.lit(j.name).alias("judge"), F.lit(n).alias("ranker"), "lists", "recall")
            out = one if out is None else out.unionAll(one)
    return out


def _k_ablation_sql() -> str:
    one = lambda key, j: f"select '{j.name}' as judge, * from ({M.k_sql(RANKER, j.with_tau(min(j.tau, WORKLOADS[key].tau)))}) z"
    each = " union all ".join(f"select * from ({derive_sql(key)}{' union all '.join(one(key, j) for j in (OLDER, NEWER))}) w{i}" for i, key in enumerate(ALL))
    return f"select judge, k, count(*) as workloads, round(avg(f1), 4) as f1, round(avg(precision), 4) as precision, round(avg(recall), 4) as recall from ({each}) e group by judge, k"


@query("exp_k_ablation", _k_ablation_sql())
def _(s, d):
    """Rates by the number of candidates kept, averaged over the workloads."""

    def rates(key):
        out, c = None, candidates(s, d, key)
        for j in (OLDER, NEWER):
            one = M.k_sweep(c, RANKER, j.with_tau(min(j.tau, WORKLOADS[key].tau))).withColumn("judge", F.lit(j.name))
            out = one if out is None else out.unionAll(one)
        return out

    return each(s, d, ALL, rates).groupBy("judge", "k").agg(F.count(F.lit(1)).alias("workloads"), *(F.round(F.avg(m), 4).alias(m) for m in ("f1", "precision", "recall")))


# --- Baselines

#: Records of the first side from which the self-supervised baseline learns, at most.
SELF_SAMPLE = 2000


def perturbed(r: DataFrame, w: Workload) -> DataFrame:
    """Records as another source may hold them: words and values missing, numbers a little off; by digests of ids, so that reruns agree."""
    u = lambda tag, *more: F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(tag), F.col("rid").cast("string"), *more)), 1, 8), 16, 10).cast("double") / 4294967296

    def other(t) -> Column:
        v = F.col(t.name)
        if t.kind in ("jaccard", "contain"):
            return F.array_join(F.filter(F.split(v, " "), lambda x, i: u(t.name, i.cast("string")) >= 0.2), " ")
        if t.kind == "lev":
            return F.when(u(t.name) < 0.5, F.substring(v, 2, 1 << 30)).otherwise(v)
        if t.kind in ("absgap", "relgap"):
            return v + F.lit(0.6 * t.scale) * (u(t.name) - 0.5) * (v if t.kind == "relgap" else F.lit(1.0))
        return F.when(u(t.name) >= 0.2, v)

    return r.select("rid", *(other(t).alias(t.name) for t in w.attributes))


def selfsup_pairs(s, d, key: str) -> DataFrame:
    """Pairs without labels of the task: records with a perturbed copy of themselves (true), and with what blocking holds most like them (false)."""
    w = WORKLOADS[key]
    d1 = side(s, d, w, "d1")
    r = d1.orderBy(F.md5(F.concat(F.lit("u|"), F.col("rid").cast("string"))), "rid").limit(SELF_SAMPLE)
    same = compared(r.select(F.col("rid").alias("anchor_id"), F.col("rid").alias("cand_id"), F.lit(1).alias("pos")), r, perturbed(r, w), w)
    other = compared(block_tfidf(r, d1, w, 3, exclude_self=True).drop("block_score"), r, d1, w)
    return same.withColumn("is_true", F.lit(True)).unionByName(other.withColumn("is_true", F.lit(False)))


BASELINES = {"supervised": (False, BL.fit_pair_classifier), "list-aware": (True, BL.fit_context_classifier), "mixture": (False, BL.fit_mixture), "self-supervised": (False, BL.fit_selfsup)}


def baseline(s, d, key: str, name: str) -> DataFrame:
    """anchor_id, cand_id, p. Where there is nothing to learn from (no training pairs, or for learners of labels no two labels), p is 0."""
    context, fit = BASELINES[name]
    c = BL.pair_features(candidates(s, d, key), context)
    train = BL.pair_features(selfsup_pairs(s, d, key) if name == "self-supervised" else M.training_pairs(s, d, key), context).select("label", *BL.features(c)).cache()
    enough = train.select("label").distinct().count() >= (1 if name == "mixture" else 2)
    out = BL.predict(fit(train), c) if enough else c.select("anchor_id", "cand_id", F.lit(0.0).alias("p"))
    train.unpersist()
    return out.select("anchor_id", "cand_id", F.round("p", 6).alias("p"))


for _name, _query in (("supervised", "baseline_supervised_linear"), ("list-aware", "baseline_supervised_listaware"), ("mixture", "baseline_unsup_mixture"), ("self-supervised", "baseline_selfsup")):
    query(_query)(lambda s, d, name=_name: baseline(s, d, W, name))


@query("baseline_features", on("w6", "select anchor_id, cand_id, coalesce(s_customer, 0.5e0) as s_customer, coalesce(s_day, 0.5e0) as s_day, coalesce(s_price, 0.5e0) as s_price, coalesce(s_priority, 0.5e0) as s_priority from cs"))
def _(s, d):
    return BL.pair_features(candidates(s, d, "w6")).select("anchor_id", "cand_id", "s_customer", "s_day", "s_price", "s_priority")


_thr = "(select sim as threshold, f1 from (select sim, round(200.0e0 * sum(t) over w / (sum(n) over w + (select count(*) from tp where is_true)), 4) as f1 from (select sim, count(*) filter (is_true) as t, count(*) as n from tp group by sim) b window w as (order by sim desc)) z order by f1 desc, sim desc limit 1)"


@query("baseline_threshold", M.train_sql(W) + f"select * from {_thr} q")
def _(s, d):
    return BL.fit_threshold(M.training_pairs(s, d, W))


@query("exp_baselines")
def baselines(s, d, keys=(W,)):
    out = None
    for key in keys:
        c = candidates(s, d, key)
        for n in BASELINES:
            one = A.prf(c, BL.decide(baseline(s, d, key, n))).select(F.lit(key).alias("workload"), F.lit(n).alias("baseline"), "tp", "fp", "fn", "precision", "recall", "f1")
            out = one if out is None else out.unionAll(one)
    return out


@query("cost_tokens_text", on("w6", M._w6_sql + "select anchor_id, cand_id, cast(len(list_filter(string_split_regex(b_text, '\\s+'), lambda w: w <> '')) as bigint) as words, cast(ceil(length(b_text) / 4.0) as bigint) as chars4 from tx"))
def _(s, d):
    return M._w6_texts(s, d).select("anchor_id", "cand_id", count_tokens(F.col("b_text")).alias("words"), count_tokens(F.col("b_text"), "chars4").alias("chars4"))
