"""Queries of the methods, measures and costs, each with its oracle."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from recmatch.functions import prompts as P
from recmatch.operators import baselines as BL
from recmatch.operators import clustering as G
from recmatch.operators import measures as A
from recmatch.operators import strategies as S
from recmatch.operators.judges import DEFAULT, LADDER, LENIENT, NEWER, OLDER, RANKER, Judge, NoProbabilities, black_box
from recmatch.plans import blocking as B
from recmatch.plans.candidates import LIST, MATCHED, UNMATCHED, anchors, candidates, compared, derive_sql, each, kept, records, sample, shared, side, tokens, truth, word_hashes
from recmatch.plans.overlap import passing
from recmatch.plans.workloads import GRAMS, WORKLOADS
from recmatch.sources.tables import sql, table

W = "w2"
QUERIES: dict = {}
ORACLES: dict[str, str] = {}
BIASED = Judge("biased", tau=0.8, delta=0.03, lam=0.02)


def query(name: str, oracle: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return keep


def on(key: str, text: str) -> str:
    return derive_sql(key) + text


# --- SQL of the strategies over cs(anchor_id, cand_id, pos, sim, is_true)

def m_sql(j: Judge, src: str = "cs") -> str:
    return f"(select *, case when p_yes >= 0.5 then true else false end as yes, round(case when p_yes >= 0.5 then 1 + p_yes else 1 - round(1 - p_yes, 6) end, 6) as score, round(1 - p_yes, 6) as p_no from (select *, {j.p_yes('oracle')} as p_yes from {src}) m0)"


def ranked_sql(scored: str, k: int = 99) -> str:
    return f"(select * from (select *, cast(row_number() over (partition by anchor_id order by score desc, pos, cand_id) as integer) as rank from {scored} r0) r1 where rank <= {k})"


def t_sql(j: Judge, src: str = "cs") -> str:
    p = j.p_first("oracle", "a_sim", "b_sim", "a_id", "b_id")
    return f"(select *, round(1 - p_a, 6) as p_b, case when p_a >= 0.5 then 'A' else 'B' end as label from (select *, {p} as p_a from (select x.anchor_id, x.cand_id as a_id, y.cand_id as b_id, x.sim as a_sim, y.sim as b_sim, x.pos as a_pos, y.pos as b_pos from {src} x join {src} y on x.anchor_id = y.anchor_id and x.pos <> y.pos) t0) t1)"


def c_sql(j: Judge, use: str = "labels", src: str = "cs") -> str:
    a, b = ("p_a", "p_b") if use == "probs" else ("case when label = 'A' then 1.0e0 else 0 end", "case when label = 'B' then 1.0e0 else 0 end")
    return f"(select c.*, coalesce(v.score, 0.0e0) as score from {src} c left join (select anchor_id, cand_id, round(sum(v), 6) as score from (select anchor_id, a_id as cand_id, {a} as v from {t_sql(j, src)} q1 union all select anchor_id, b_id, {b} from {t_sql(j, src)} q2) u group by anchor_id, cand_id) v using (anchor_id, cand_id))"


def s_sql(j: Judge, opt_out: bool, src: str = "cs") -> str:
    keep = f"most >= {j.least}e0" if opt_out else "true"
    return f"(select anchor_id, cast(case when {keep} then pos else 0 end as integer) as choice, case when {keep} then cand_id end as cand_id from (select *, max({j.held('oracle')}) over (partition by anchor_id) as most, row_number() over (partition by anchor_id order by {j.worth('oracle')} desc, pos) as rn from {src}) s0 where rn = 1)"


def bubble_sql(k: int, src: str = "cs") -> str:
    """An unbiased judge without noise orders as its similarity does."""
    return f"(select * from (select *, cast(row_number() over (partition by anchor_id order by sim desc, pos) as integer) as rank from {src}) b0 where rank <= {k})"


def short_sql(ranker: str, j: Judge, k: int) -> str:
    src = {"match": ranked_sql(m_sql(j), k), "allpair": ranked_sql(c_sql(j), k), "bubble": bubble_sql(k), "block": f"(select *, pos as rank from cs where pos <= {k})"}[ranker]
    return f"(select anchor_id, cand_id, cast(rank as integer) as pos, sim, is_true from {src} k0)"


def x_sql(ranker: str, jr: Judge, js: Judge, k: int = 4) -> str:
    return s_sql(js, True, short_sql(ranker, jr, k))


def rates_sql() -> str:
    return "tp, fp, fn, round(100.0e0 * tp / nullif(tp + fp, 0), 4) as precision, round(100.0e0 * tp / nullif(tp + fn, 0), 4) as recall, round(200.0e0 * tp / nullif(2 * tp + fp + fn, 0), 4) as f1"


def prf_sql(dec: str, extra: str = "") -> str:
    return f"select {extra}{rates_sql()} from (select tp, fp, (select count(*) from cs where is_true) - tp as fn from (select count(*) filter (t) as tp, count(*) filter (not t) as fp from (select d.anchor_id, d.cand_id, coalesce(cs.is_true, false) as t from {dec} d left join cs using (anchor_id, cand_id) where d.cand_id is not null) a0) a1) a2"


def yes_sql(j: Judge) -> str:
    return f"(select anchor_id, cand_id from {m_sql(j)} y0 where yes)"


def pass_sql(j: Judge) -> str:
    """The winner of one bubble pass from the tail by a noisy judge, comparison by comparison."""
    wins = f"({j.p_first('oracle', 'b.sim', 'p.sim', 'b.cand_id', 'p.cand_id', 'b.anchor_id')} >= 0.5 and {j.p_first('oracle', 'p.sim', 'b.sim', 'p.cand_id', 'b.cand_id', 'b.anchor_id')} < 0.5)"
    return f"""(with recursive p as (select *, row_number() over (partition by anchor_id order by pos) as slot, count(*) over (partition by anchor_id) as n from cs),
 b as (select anchor_id, n as place, cand_id, sim from p where slot = n
 union all select b.anchor_id, b.place - 1, case when {wins} then b.cand_id else p.cand_id end, case when {wins} then b.sim else p.sim end from b join p on p.anchor_id = b.anchor_id and p.slot = b.place - 1)
 select anchor_id, cand_id, sim from b where place = 1)"""


def identify_sql(jc: Judge, jm: Judge) -> str:
    return f"(select anchor_id, case when yes then cand_id end as cand_id from {m_sql(jm, pass_sql(jc) if jc.sigma_triple or jc.sigma_record else bubble_sql(1))} i0)"


# --- Pairwise

@query("match_decide", on(W, f"select anchor_id, cand_id, yes from {m_sql(DEFAULT)} q"))
def _(s, d):
    return S.match_pairs(candidates(s, d, W), DEFAULT).select("anchor_id", "cand_id", "yes")


@query("match_score", on(W, f"select anchor_id, cand_id, p_yes, p_no, score from {m_sql(DEFAULT)} q"))
def _(s, d):
    return S.match_scores(candidates(s, d, W), DEFAULT).select("anchor_id", "cand_id", "p_yes", "p_no", "score")


@query("match_score_blackbox", on(W, f"select anchor_id, cand_id, case when yes then 1.0e0 else 0.0e0 end as score from {m_sql(DEFAULT)} q"))
def _(s, d):
    return S.match_scores(candidates(s, d, W), black_box(DEFAULT), "label").select("anchor_id", "cand_id", "score")


@query("match_rank_topk", on(W, f"select anchor_id, cand_id, rank, score from {ranked_sql(m_sql(LENIENT), 4)} q"))
def _(s, d):
    return S.rank_by_match(candidates(s, d, W), LENIENT, 4).select("anchor_id", "cand_id", "rank", "score")


@query("match_top1", on(W, f"select anchor_id, case when yes then cand_id end as cand_id from {ranked_sql(m_sql(LENIENT), 1)} q"))
def _(s, d):
    return S.match_best(candidates(s, d, W), LENIENT)


def training_anchors(s: SparkSession, d: str, key: str, n: int = 5000) -> DataFrame:
    """Records of so many anchors outside the evaluation sample as have n pairs, stored."""

    def make():
        d1 = side(s, d, WORKLOADS[key], "d1")
        rest = d1.join(F.broadcast(anchors(s, d, key).select("rid")), "rid", "left_anti")
        few = rest.select("rid").orderBy(F.md5(F.concat(F.lit("t|"), F.col("rid").cast("string"))), "rid").limit(-(-n // LIST))
        return d1.join(F.broadcast(few), "rid", "left_semi")

    return kept(s, (d, key, f"rest{n}"), make)


def training_pairs(s: SparkSession, d: str, key: str, n: int = 5000) -> DataFrame:
    """Labelled pairs of anchors outside the evaluation sample, the first n in the order of a digest."""

    def make():
        w, true = WORKLOADS[key], truth(s, d, key)
        rest, d2 = training_anchors(s, d, key, n), records(s, d, key)
        found = kept(s, (d, key, f"found{n}"), lambda: B.block_tfidf(rest, d2, w, LIST, lists=tokens(s, d, key)))
        few = d2.join(F.broadcast(found.select(F.col("cand_id").alias("rid")).distinct()), "rid", "left_semi")  # n rows at most
        pairs = compared(found, rest, few, w)
        return pairs.join(true.withColumn("t", F.lit(True)), ["anchor_id", "cand_id"], "left").withColumn("is_true", F.coalesce("t", F.lit(False))).drop("t").orderBy(F.md5(F.concat(F.col("anchor_id").cast("string"), F.lit("|"), F.col("cand_id").cast("string"))), "anchor_id", "cand_id").limit(n)

    return kept(s, (d, key, "train"), make)


def train_sql(key: str, n: int = 5000) -> str:
    """derive_sql with the training anchors in place of the sample: cs holds their pairs, tp the picked ones."""
    text = derive_sql(key)
    out = text.replace("picked as (select d1.*", "sampled as (select d1.*", 1)
    pick = f"picked as (select * from d1 where rid not in (select rid from sampled) order by md5(concat('t|', cast(rid as varchar))), rid limit {-(-n // LIST)}), "
    at = out.index("idx as (")
    return f"{out[:at]}{pick}{out[at:]}, tp as (select * from cs order by md5(concat(cast(anchor_id as varchar), '|', cast(cand_id as varchar))), anchor_id, cand_id limit {n})\n"


@query("workload_train_pairs", train_sql(W) + "select anchor_id, cand_id, is_true, sim from tp")
def _(s, d):
    return training_pairs(s, d, W).select("anchor_id", "cand_id", "is_true", "sim")


def examples(s: SparkSession, d: str, key: str) -> DataFrame:
    """Three like and three unlike labelled pairs for each evaluation anchor, from all training pairs."""

    def make():
        return S.retrieve_examples(anchors(s, d, key), training_anchors(s, d, key), training_pairs(s, d, key), WORKLOADS[key])

    return kept(s, (d, key, "examples"), make)


def examples_sql(key: str) -> str:
    """Common table expressions after those of derive_sql, ending in ex."""
    near = B.blocking_sql(replace(WORKLOADS[key], max_df=S.EXAMPLE_DF), "picked", 3)
    one = lambda label, having: f"select anchor_id, {label} as label, cast(row_number() over (partition by anchor_id order by pos, ex_c) as integer) as n, ex_a, ex_c, ex_sim from (with d2 as (select * from d1 where rid in (select ex_a from pool where {having})), {near} select anchor_id, cand_id as ex_a, pos from cand) near{label} join pool using (ex_a) where {having}"
    return f", pool as ({train_sql(key)} select anchor_id as ex_a, cand_id as ex_c, sim as ex_sim, is_true from tp), ex as (select * from ({one(1, 'is_true')} union all {one(0, 'not is_true')}) e0 where n <= 3) "


def fewshot_sql(j: Judge) -> str:
    """Over cs and ex: cs with shift and yes."""
    return f"(select *, {j.p_yes('oracle', '(sim - shift)')} >= 0.5 as yes from (select cs.*, round(coalesce((up + down) / 2 - {j.tau}e0, 0.0e0) + 1e-9, 6) as shift from cs left join (select anchor_id, avg(ex_sim) filter (label = 1) as up, avg(ex_sim) filter (label = 0) as down from ex group by anchor_id) f0 using (anchor_id)) f1)"


@query("fewshot_examples", on(W, examples_sql(W) + "select * from ex"))
def _(s, d):
    return examples(s, d, W)


@query("match_fewshot", on(W, examples_sql(W) + f"select anchor_id, cand_id, shift, yes from {fewshot_sql(LENIENT)} q"))
def fewshot(s, d):
    return S.match_fewshot(candidates(s, d, W), LENIENT, examples(s, d, W)).select("anchor_id", "cand_id", "shift", "yes")


def record_words(s: SparkSession, d: str, key: str, which: str) -> DataFrame:
    """rid, words: how long each record of a side is in a prompt."""
    w = WORKLOADS[key]
    return side(s, d, w, which).select("rid", P.count_tokens(P.record_text([t.name for t in w.attributes], "")).alias("words"))


def words_sql(key: str, which: str) -> str:
    text = "concat_ws('; ', " + ", ".join(f"'{t.name}: ' || cast({t.name} as varchar)" for t in WORKLOADS[key].attributes) + ")"
    return f"(select rid, cast(len(list_filter(string_split_regex({text}, '\\s+'), lambda w: w <> '')) as bigint) as words from {which})"


_rec = "concat_ws('; ', concat('customer: ', customer), concat('day: ', cast(day as varchar)), concat('priority: ', priority))"
_w6 = [t for t in ("customer", "day", "priority")]


def _w6_texts(s, d):
    w = WORKLOADS["w6"]
    a = side(s, d, w, "d1").select(F.col("rid").alias("anchor_id"), P.record_text(_w6, "").alias("a_text"))
    b = side(s, d, w, "d2").select(F.col("rid").alias("cand_id"), P.record_text(_w6, "").alias("b_text"))
    return candidates(s, d, "w6").join(a, "anchor_id").join(b, "cand_id")


_w6_sql = f", atx as (select rid as anchor_id, {_rec} as a_text from d1), bt as (select rid as cand_id, {_rec} as b_text from d2), tx as (select cs.*, a_text, b_text from cs join atx using (anchor_id) join bt using (cand_id)) "


@query("match_prompt", on("w6", _w6_sql + "select anchor_id, cand_id, md5(concat_ws(chr(10), 'Say Yes if both entries describe one real thing, else No.', concat('First: ', a_text), concat('Second: ', b_text))) as digest from tx"))
def _(s, d):
    return _w6_texts(s, d).select("anchor_id", "cand_id", F.md5(P.render_pair(F.col("a_text"), F.col("b_text"))).alias("digest"))


@query("compare_prompt", on("w6", _w6_sql + "select x.anchor_id, x.cand_id as a_id, y.cand_id as b_id, md5(concat_ws(chr(10), 'Which entry fits the given one better, A or B?', concat('Given: ', x.a_text), concat('A: ', x.b_text), concat('B: ', y.b_text))) as digest from tx x join tx y on x.anchor_id = y.anchor_id and x.pos <> y.pos"))
def _(s, d):
    t = _w6_texts(s, d).select("anchor_id", "cand_id", "pos", "a_text", "b_text")
    x, y = t.alias("x"), t.alias("y")
    both = x.join(y, (F.col("x.anchor_id") == F.col("y.anchor_id")) & (F.col("x.pos") != F.col("y.pos")))
    return both.select("x.anchor_id", F.col("x.cand_id").alias("a_id"), F.col("y.cand_id").alias("b_id"), F.md5(P.render_triple(F.col("x.a_text"), F.col("x.b_text"), F.col("y.b_text"))).alias("digest"))


@query("select_prompt", on("w6", _w6_sql + "select anchor_id, md5(concat_ws(chr(10), 'Give the number of the entry that describes the same thing.', concat('Given: ', max(a_text)), string_agg(concat(cast(pos as varchar), ': ', b_text), chr(10) order by pos), '0: none of these')) as digest from tx group by anchor_id"))
def _(s, d):
    g = _w6_texts(s, d).groupBy("anchor_id").agg(F.max("a_text").alias("a_text"), F.array_sort(F.collect_list(F.struct("pos", "b_text"))).alias("o"))  # at most 10 candidates
    return g.select("anchor_id", F.md5(P.render_list(F.col("a_text"), F.col("o.b_text"), True)).alias("digest"))


def _texts(s, d):
    """Every document's text stands for an answer."""
    return table(s, d, "documents").select(F.col("doc_id").alias("n"), F.col("text").alias("answer"))


_texts_sql = "(select doc_id as n, text as answer from documents) t"


@query("match_parse", f"select n, case when y and not o then 'true' when o and not y then 'false' end as parsed from (select n, regexp_matches(lower(answer), '(^|[^a-z])yes([^a-z]|$)') as y, regexp_matches(lower(answer), '(^|[^a-z])no([^a-z]|$)') as o from {_texts_sql}) q")
def _(s, d):
    return _texts(s, d).select("n", P.parse_yes_no(F.col("answer")).cast("string").alias("parsed"))


@query("compare_parse", f"select n, case when y and not o then 'A' when o and not y then 'B' end as parsed from (select n, regexp_matches(answer, '(^|[^A-Za-z])A([^A-Za-z]|$)') as y, regexp_matches(answer, '(^|[^A-Za-z])B([^A-Za-z]|$)') as o from {_texts_sql}) q")
def _(s, d):
    return _texts(s, d).select("n", P.parse_ab(F.col("answer")).alias("parsed"))


@query("select_parse", f"select n, case when v <= 10 then v end as parsed from (select n, try_cast(regexp_extract(answer, '([0-9]+)', 1) as integer) as v from {_texts_sql}) q")
def _(s, d):
    return _texts(s, d).select("n", P.parse_choice(F.col("answer"), F.lit(10)).alias("parsed"))


# --- Triplewise

@query("compare_triples", on(W, f"select anchor_id, a_id, b_id, p_a, p_b, label from {t_sql(BIASED)} q"))
def _(s, d):
    return S.compare_triples(candidates(s, d, W), BIASED).select("anchor_id", "a_id", "b_id", "p_a", "p_b", "label")


_out_sql = f"(select anchor_id, case when a_pos < b_pos then a_id else b_id end as i_id, case when a_pos < b_pos then b_id else a_id end as j_id, cast(sum(case when (a_pos < b_pos) = (label = 'A') then 1 else 0 end) as integer) as wins from {t_sql(BIASED)} o0 group by 1, 2, 3)"


@query("compare_outcome", on(W, f"select * from {_out_sql} q"))
def _(s, d):
    return S.compare_outcomes(S.compare_triples(candidates(s, d, W), BIASED))


@query("compare_score_labels", on(W, f"select anchor_id, cand_id, score from {c_sql(DEFAULT)} q"))
def _(s, d):
    return S.compare_scores(candidates(s, d, W), DEFAULT).select("anchor_id", "cand_id", "score")


@query("compare_score_probs", on(W, f"select anchor_id, cand_id, score from {c_sql(DEFAULT, 'probs')} q"))
def _(s, d):
    return S.compare_scores(candidates(s, d, W), DEFAULT, "probs").select("anchor_id", "cand_id", "score")


@query("compare_allpair_rank", on(W, f"select anchor_id, cand_id, rank from {ranked_sql(c_sql(DEFAULT), 4)} q"))
def _(s, d):
    return S.rank_by_allpair(candidates(s, d, W), DEFAULT, 4).select("anchor_id", "cand_id", "rank")


@query("compare_bubble_topk", on(W, f"select anchor_id, cand_id, rank from {bubble_sql(4)} q"))
def _(s, d):
    return S.rank_by_bubble(candidates(s, d, W), DEFAULT, 4).select("anchor_id", "cand_id", "rank")


@query("compare_identify", on(W, f"select * from {identify_sql(DEFAULT, LENIENT)} q"))
def _(s, d):
    return S.compare_identify(candidates(s, d, W), DEFAULT, LENIENT)


@query("compare_order_sensitivity", on(W, f"select count(*) as pairs, cast(sum(case when wins = 1 then 1 else 0 end) as bigint) as flips, round(avg(case when wins = 1 then 1.0e0 else 0 end), 6) as flip_rate from {_out_sql} q"))
def _(s, d):
    return S.order_flip_rate(S.compare_triples(candidates(s, d, W), BIASED))


# --- Listwise

@query("select_forced", on(W, f"select * from {s_sql(DEFAULT, False)} q"))
def _(s, d):
    return S.select(candidates(s, d, W), DEFAULT)


@query("select_optout", on(W, f"select * from {s_sql(DEFAULT, True)} q"))
def flagship(s, d):
    return S.select(candidates(s, d, W), DEFAULT, True)


@query("select_verify", on(W, f"select anchor_id, case when yes then cand_id end as cand_id from (select m.* from {m_sql(LENIENT)} m join {s_sql(DEFAULT, False)} c using (anchor_id, cand_id)) q"))
def _(s, d):
    return S.select_then_verify(candidates(s, d, W), DEFAULT, LENIENT)


_placed_sql = """, full1 as (select *, count(*) over (partition by anchor_id) as size, sum(case when is_true then 1 else 0 end) over (partition by anchor_id) as has, max(case when is_true then pos end) over (partition by anchor_id) as tpos from cs),
 slots as (select cast(range as integer) as slot from range(1, 11)),
 placed as (select anchor_id, cand_id, sim, is_true, slot, cast(case when is_true then slot else pos - (case when pos > tpos then 1 else 0 end) + (case when pos - (case when pos > tpos then 1 else 0 end) >= slot then 1 else 0 end) end as integer) as pos from full1, slots where size = 10 and has = 1)
"""


def position(cands: DataFrame, choose) -> DataFrame:
    """slot, lists, right, accuracy of a choice on lists with the true candidate in each slot."""
    p = S.place_at(cands).withColumn("list_id", F.col("anchor_id")).withColumn("anchor_id", F.col("anchor_id") * 100 + F.col("slot"))
    got = choose(p).select("anchor_id", F.col("cand_id").alias("got"))
    t = p.filter("is_true").select("anchor_id", "slot", "cand_id").join(got, "anchor_id")
    return t.groupBy("slot").agg(F.count(F.lit(1)).alias("lists"), F.count_if(F.col("got").eqNullSafe(F.col("cand_id"))).alias("right")).select("slot", "lists", "right", F.round(F.col("right") / F.col("lists"), 6).alias("accuracy"))


def position_sql(dec) -> str:
    src = "(select anchor_id * 100 + slot as anchor_id, cand_id, pos, sim, is_true, slot from placed)"
    return _placed_sql + f"select p.slot, count(*) as lists, count(*) filter (c.cand_id is not distinct from p.cand_id) as right, round(count(*) filter (c.cand_id is not distinct from p.cand_id) / cast(count(*) as double), 6) as accuracy from {src} p join {dec(src)} c using (anchor_id) where p.is_true group by p.slot"


PLACED = Judge("place-shy", tau=0.8, lam=0.04)
ORACLES["select_position_bias"] = on(W, position_sql(lambda src: s_sql(PLACED, False, src)).replace(" as right", ' as "right"'))


@query("select_position_bias")
def _(s, d):
    return position(candidates(s, d, W), lambda p: S.select(p, PLACED))


def _compound_on(src: str) -> str:
    return s_sql(PLACED, True, f"(select anchor_id, cand_id, cast(rank as integer) as pos, sim, is_true from {ranked_sql(m_sql(PLACED, src), 4)} k0)")


ORACLES["compound_position_curve"] = on(W, position_sql(_compound_on).replace(" as right", ' as "right"'))


@query("compound_position_curve")
def _(s, d):
    return position(candidates(s, d, W), lambda p: S.compound(p, PLACED, PLACED))


@query("select_context_budget", on("w6", _w6_sql + "select anchor_id, cand_id, used from (select *, cast(sum(len(list_filter(string_split_regex(b_text, '\\s+'), lambda w: w <> ''))) over (partition by anchor_id order by pos) as bigint) as used from tx) q where used <= 40"))
def _(s, d):
    return S.fit_context(_w6_texts(s, d), P.count_tokens(F.col("b_text")), 40).select("anchor_id", "cand_id", "used")


@query("select_one_to_one", on(W, f"select anchor_id, count(*) as n from {s_sql(DEFAULT, True)} q where cand_id is not null group by anchor_id having count(*) > 1"))
def _(s, d):
    return S.select(candidates(s, d, W), DEFAULT, True).filter("cand_id is not null").groupBy("anchor_id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")


# --- Graphs

_e_sql = f"(select anchor_id as src_id, cand_id as dst_id, score as weight from {m_sql(LENIENT)} e0 where score >= 1)"


def _edges(s, d):
    return G.similarity_edges(S.match_scores(candidates(s, d, W), LENIENT), 1.0)


@query("graph_edges", on(W, f"select * from {_e_sql} q"))
def _(s, d):
    return _edges(s, d)


_dedup_sql = f"with recursive g as ({GRAMS['oracle']}), pairs as (select a.rid as u, b.rid as v from g a join g b on a.gram = b.gram and a.rid <> b.rid group by a.rid, b.rid having count(*) >= 0.4 * (max(a.n) + max(b.n) - count(*))), reach as (select distinct u as rid, u as other from pairs union select r.rid, p.v from reach r join pairs p on r.other = p.u), members as (select rid, min(other) as cluster_id from reach group by rid) "


def _dedup(s, d, least: float = 0.4):
    """Edges of the deduplication workload: documents whose word grams overlap, found by MinHash bands and verified."""

    def make():
        docs = word_hashes(s, d)
        if docs is not None:
            return B.block_minhash_words(docs, store, bands=40, rows=2, least=least).select(F.col("anchor_id").alias("src_id"), F.col("cand_id").alias("dst_id"), F.col("block_score").alias("weight"))
        g = sql(s, d, GRAMS["spark"]).groupBy("rid").agg(F.collect_list(F.xxhash64("gram")).alias("grams"))  # a document's own grams, 8 bytes each
        g = kept(s, (d, "w9", "grams"), lambda: g)
        return B.block_minhash(g, g, bands=40, rows=2, least=least).select(F.col("anchor_id").alias("src_id"), F.col("cand_id").alias("dst_id"), F.col("block_score").alias("weight"))

    with passing(s, shared(s)) as store:
        return kept(s, (d, "w9", "edges", least), make)


@query("graph_components", _dedup_sql + "select rid, cluster_id from members")
def components(s, d):
    from recmatch.plans.candidates import shared

    shared(s)
    return G.connected_components(_dedup(s, d))


@query("graph_mutual_best", on(W, f"select src_id, dst_id, weight from (select *, row_number() over (partition by src_id order by weight desc, dst_id) as rs, row_number() over (partition by dst_id order by weight desc, src_id) as rd from {_e_sql} q) m where rs = 1 and rd = 1"))
def _(s, d):
    return G.mutual_best(_edges(s, d))


@query("graph_one_to_one")
def _(s, d):
    from recmatch.plans.candidates import shared

    shared(s)
    return G.greedy_matching(_edges(s, d))


@query("graph_canonical", _dedup_sql + "select cluster_id, arg_max(rid, {'a': n_chars, 'b': -rid}) as canonical_id, count(*) as members from members join (select doc_id as rid, n_chars from documents) x using (rid) group by cluster_id")
def _(s, d):
    return G.canonicalise(components(s, d), table(s, d, "documents").select(F.col("doc_id").alias("rid"), "n_chars"), "n_chars")


@query("global_consistency_rate", on(W, f"select (select count(*) from (select anchor_id from {yes_sql(LENIENT)} a group by anchor_id having count(*) > 1) x) as anchors_with_many, (select count(distinct anchor_id) from {yes_sql(LENIENT)} b) as anchors, (select count(*) from (select cand_id from {yes_sql(LENIENT)} c group by cand_id having count(*) > 1) y) as cands_with_many, (select count(distinct cand_id) from {yes_sql(LENIENT)} e) as cands"))
def _(s, d):
    return G.consistency_report(S.match_pairs(candidates(s, d, W), LENIENT).filter("yes").select("anchor_id", "cand_id"))


# --- Compound

def _compound(name: str, ranker: str, jr: Judge, js: Judge, oracle: bool = True):
    @query(name, on(W, f"select * from {x_sql(ranker, jr, js)} q") if oracle else None)
    def _(s, d):
        return S.compound(candidates(s, d, W), jr, js, ranker)


_compound("compound_match_select", "match", RANKER, LENIENT)
_compound("compound_bubble_select", "bubble", DEFAULT, LENIENT)
_compound("compound_allpair_select", "allpair", DEFAULT, LENIENT)
_compound("compound_single_judge", "match", LENIENT, LENIENT)
_compound("compound_block_only", "block", LENIENT, LENIENT)


def k_sweep(cands: DataFrame, jr: Judge, js: Judge, ks=range(1, 11)) -> DataFrame:
    """Rates for each k. The ranking is made once; each k is a slice of it."""
    ranked = S.rank_by_match(cands, jr).select("anchor_id", "cand_id", F.col("rank").cast("int").alias("pos"), "sim", "is_true")
    lists = ranked.withColumn("k", F.explode(F.array(*map(F.lit, ks)))).filter("pos <= k")
    dec = S.select(lists, js, True, ("anchor_id", "k")).filter("cand_id is not null")
    got = dec.join(cands.select("anchor_id", "cand_id", "is_true"), ["anchor_id", "cand_id"]).groupBy("k").agg(F.count_if("is_true").alias("tp"), F.count_if(~F.col("is_true")).alias("fp"))
    one = got.join(F.broadcast(cands.agg(F.count_if("is_true").alias("n")))).select("k", "tp", "fp", (F.col("n") - F.col("tp")).alias("fn"))
    return one.select("k", "tp", "fp", "fn", *A.rates(F.col("tp"), F.col("fp"), F.col("fn")))


def k_sql(jr: Judge, js: Judge) -> str:
    return " union all ".join(prf_sql(x_sql("match", jr, js, k), f"cast({k} as integer) as k, ") for k in range(1, 11))


@query("compound_k_sweep", on(W, k_sql(RANKER, PLACED)))
def _(s, d):
    return k_sweep(candidates(s, d, W), RANKER, PLACED)


# --- Blocking

def _blocked(name: str, key: str, n: int = LIST, saturated=None):
    ctes = derive_sql(key, n=n)
    if saturated:
        plain_ctes, sat = B.blocking_sql(WORKLOADS[key], "picked", n), B.blocking_sql(WORKLOADS[key], "picked", n, saturated=saturated)
        ctes = ctes.replace(plain_ctes, sat)

    @query(name, ctes + "select anchor_id, cand_id, pos, block_score from cand")
    def _(s, d):
        w = WORKLOADS[key]
        d1, d2 = side(s, d, w, "d1"), side(s, d, w, "d2")
        return B.block_tfidf(d1.join(sample(d1, truth(s, d, key)), "rid", "left_semi"), d2, w, n, saturated=saturated)


_blocked("block_tfidf_topn", W)
_blocked("block_bm25_topn", W, saturated=(1.2, 0.75))

_near_sql = "select anchor_id, cand_id, pos, block_score from (select *, cast(row_number() over (partition by anchor_id order by block_score desc, cand_id) as integer) as pos from sc) q where pos <= 10"
_vec_sql = f"with q as (select vec_id, embedding from embeddings where vec_id % 25 = 0), sc as (select q.vec_id as anchor_id, e.vec_id as cand_id, round(list_dot_product(q.embedding::double[], e.embedding::double[]) / sqrt(list_dot_product(q.embedding::double[], q.embedding::double[]) * list_dot_product(e.embedding::double[], e.embedding::double[])), 6) as block_score from q, embeddings e) {_near_sql}"


def _vectors(s, d):
    v = table(s, d, "embeddings").select(F.col("vec_id").alias("rid"), F.col("embedding").alias("v"))
    return v.filter("rid % 25 = 0"), v


@query("block_vector_topn", _vec_sql)
def _(s, d):
    return B.block_vectors(*_vectors(s, d))


@query("block_vector_lsh")
def _(s, d):
    return B.block_vectors(*_vectors(s, d), planes=4, reach=3)


_brute_sql = f", sc as (select c.rid as anchor_id, d2.rid as cand_id, cast(len(list_intersect(c.t, d2.t)) as double) as block_score from (select rid, {B.tokens_of(WORKLOADS['w7'], 'oracle')} as t from picked) c, (select rid, {B.tokens_of(WORKLOADS['w7'], 'oracle')} as t from d2) d2) "


@query("block_bruteforce", on("w7", _brute_sql + _near_sql))
def _(s, d):
    w = WORKLOADS["w7"]
    t = lambda x: x.select("rid", F.expr(B.tokens_of(w, "spark")).alias("t"))
    d1 = side(s, d, w, "d1")
    few = F.broadcast(t(d1.join(sample(d1, truth(s, d, "w7")), "rid", "left_semi")).withColumnsRenamed({"rid": "anchor_id", "t": "at"}))  # the sample, at most 400 rows
    both = few.crossJoin(t(side(s, d, w, "d2")).withColumnRenamed("rid", "cand_id"))
    return B.top_n(both.select("anchor_id", "cand_id", F.size(F.array_intersect("at", "t")).cast("double").alias("block_score")), LIST)


_gram_pairs = f"with g as ({GRAMS['oracle']}) select a.rid as anchor_id, b.rid as cand_id, round(count(*) / cast(max(a.n) + max(b.n) - count(*) as double), 6) as block_score from g a join g b on a.gram = b.gram and a.rid <> b.rid group by a.rid, b.rid having count(*) >= 0.4 * (max(a.n) + max(b.n) - count(*))"


@query("block_minhash", _gram_pairs)
def _(s, d):
    return _dedup(s, d).select(F.col("src_id").alias("anchor_id"), F.col("dst_id").alias("cand_id"), F.col("weight").alias("block_score"))


@query("block_key", "select a.c_custkey as anchor_id, b.s_suppkey as cand_id from customer a join supplier b on a.c_nationkey = b.s_nationkey")
def _(s, d):
    a = table(s, d, "customer").select(F.col("c_custkey").alias("rid"), F.col("c_nationkey").alias("k"))
    return B.block_key(a, table(s, d, "supplier").select(F.col("s_suppkey").alias("rid"), F.col("s_nationkey").alias("k")), ["k"])


_self = "with d2 as (select 10 * p_partkey as rid, p_name as name, p_brand as brand, p_type as type, cast(p_size as double) as size from part), ask0 as (select * from d2), " + B.blocking_sql(WORKLOADS[W], "ask0", 5, True)


@query("block_self", _self + " select anchor_id, cand_id, pos, block_score from cand")
def _(s, d):
    r = table(s, d, "part").select((10 * F.col("p_partkey")).alias("rid"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").cast("double").alias("size"))
    return B.block_same(r, WORKLOADS[W], 5, lambda name, make: kept(s, (d, "parts", name), make))


_recall_sql = ", t as (select t.anchor_id, (select min(pos) from cs where cs.anchor_id = t.anchor_id and cs.is_true) as pos from (select distinct anchor_id from truth where anchor_id in (select rid from picked)) t) select cast(k as integer) as k, count(*) as anchors, round(avg(case when pos <= k then 1.0e0 else 0 end), 6) as recall from t, (values (1), (3), (10)) v(k) group by k"


def blocking_recall(s, d, key):
    true = truth(s, d, key).select("anchor_id").distinct()
    first = candidates(s, d, key).filter("is_true").groupBy("anchor_id").agg(F.min("pos").alias("pos"))
    w = WORKLOADS[key]
    d1 = side(s, d, w, "d1")
    t = sample(d1, truth(s, d, key)).filter("is_matched").select(F.col("rid").alias("anchor_id")).join(true, "anchor_id", "left_semi").join(first, "anchor_id", "left")
    return t.withColumn("k", F.explode(F.array(F.lit(1), F.lit(3), F.lit(10)))).groupBy("k").agg(F.count(F.lit(1)).alias("anchors"), F.round(F.avg(F.coalesce((F.col("pos") <= F.col("k")).cast("double"), F.lit(0.0))), 6).alias("recall"))


@query("block_recall_at_n", on(W, _recall_sql))
def _(s, d):
    return blocking_recall(s, d, W)


# --- Measures

@query("metric_prf", on(W, prf_sql(s_sql(LENIENT, True))))
def _(s, d):
    c = candidates(s, d, W)
    return A.prf(c, S.select(c, LENIENT, True))


@query("metric_recall_at_1", on(W, f"select cast(k as integer) as k, count(*) as lists, round(avg(case when rank <= k then 1.0e0 else 0 end), 6) as recall from (select anchor_id, min(rank) as rank from {ranked_sql(m_sql(LENIENT))} q where is_true group by anchor_id) t, (values (1), (3), (4), (10)) v(k) group by k"))
def _(s, d):
    return A.ranking_recall(S.rank_by_match(candidates(s, d, W), LENIENT))


@query("metric_f1_by_position", on(W, f"select pos, lists, hits, wrong, round(100.0e0 * hits / lists, 4) as recall, round(200.0e0 * hits / (hits + wrong + lists), 4) as f1 from (select cs.pos, count(*) as lists, count(*) filter (q.cand_id = cs.cand_id) as hits, count(*) filter (q.cand_id <> cs.cand_id) as wrong from cs left join (select anchor_id, cand_id from {s_sql(PLACED, True)} p where cand_id is not null) q using (anchor_id) where is_true group by cs.pos) z"))
def _(s, d):
    c = candidates(s, d, W)
    q = S.select(c, PLACED, True).filter("cand_id is not null").select("anchor_id", F.col("cand_id").alias("chosen"))
    by = c.filter("is_true").join(q, "anchor_id", "left").groupBy("pos").agg(F.count(F.lit(1)).alias("lists"), F.count_if(F.col("chosen") == F.col("cand_id")).alias("hits"), F.count_if(F.col("chosen") != F.col("cand_id")).alias("wrong"))
    return by.withColumn("recall", F.round(100.0 * F.col("hits") / F.col("lists"), 4)).withColumn("f1", F.round(200.0 * F.col("hits") / (F.col("hits") + F.col("wrong") + F.col("lists")), 4))


@query("metric_selection_accuracy", on(W, f"select count(*) as lists, round(avg(case when want is not distinct from q.cand_id then 1.0e0 else 0 end), 6) as accuracy from (select anchor_id, min(case when is_true then cand_id end) as want from cs group by anchor_id) t join {s_sql(LENIENT, True)} q using (anchor_id)"))
def _(s, d):
    c = candidates(s, d, W)
    return A.selection_accuracy(c, S.select(c, LENIENT, True))


STRATEGIES = ("pairwise", "triplewise", "listwise", "compound")


def decide(cands: DataFrame, name: str, j: Judge) -> DataFrame:
    """Decisions of a strategy by one judge; the compound's ranker is the cheap one."""
    if name == "pairwise":
        return S.match_pairs(cands, j).filter("yes").select("anchor_id", "cand_id")
    if name == "triplewise":
        return S.compare_identify(cands, j, j)
    if name == "listwise":
        return S.select(cands, j, True).select("anchor_id", "cand_id")
    return S.compound(cands, RANKER, j).select("anchor_id", "cand_id")


def decide_sql(name: str, j: Judge) -> str:
    return {"pairwise": yes_sql(j), "triplewise": identify_sql(j, j), "listwise": s_sql(j, True), "compound": x_sql("match", RANKER, j)}[name]


def by_strategy(s, d, keys, judges, names=STRATEGIES) -> DataFrame:
    parts = []
    for key in keys:
        c = candidates(s, d, key)
        for j in judges:
            jj = j.with_tau(min(j.tau, WORKLOADS[key].tau))
            for n in names:
                parts.append(A.prf(c, decide(c, n, jj)).select(F.lit(key).alias("workload"), F.lit(j.name).alias("judge"), F.lit(n).alias("strategy"), "tp", "fp", "fn", "precision", "recall", "f1"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    return out


def by_strategy_sql(key, judges, names=STRATEGIES) -> str:
    return " union all ".join(prf_sql(decide_sql(n, j.with_tau(min(j.tau, WORKLOADS[key].tau))), f"'{key}' as workload, '{j.name}' as judge, '{n}' as strategy, ") for j in judges for n in names)


@query("metric_false_positive_profile", on(W, by_strategy_sql(W, [LENIENT])))
def _(s, d):
    return by_strategy(s, d, [W], [LENIENT])


@query("metric_relative_gain", on(W, f", f as ({by_strategy_sql(W, [LENIENT])}) select a.strategy, b.strategy as other, round(a.f1 - b.f1, 4) as gain from f a join f b on a.strategy > b.strategy"))
def _(s, d):
    f = by_strategy(s, d, [W], [LENIENT]).select("strategy", "f1")
    return f.alias("a").join(f.alias("b"), F.col("a.strategy") > F.col("b.strategy")).select("a.strategy", F.col("b.strategy").alias("other"), F.round(F.col("a.f1") - F.col("b.f1"), 4).alias("gain"))


@query("metric_cluster_prf", _dedup_sql + ", t as (select u as a, v as b from pairs where u < v), made as (select cast(coalesce(sum(n * (n - 1) / 2), 0) as bigint) as made from (select count(*) as n from members group by cluster_id)), " + f"r as (select (select count(*) from t join members x on x.rid = a join members y on y.rid = b where x.cluster_id = y.cluster_id) as tp, made, (select count(*) from t) as want from made) select {rates_sql()} from (select tp, made - tp as fp, want - tp as fn from r)")
def _(s, d):
    return A.cluster_prf(components(s, d), _dedup(s, d).filter("src_id < dst_id").select(F.col("src_id").alias("a"), F.col("dst_id").alias("b")))


MEAN = tuple(f"w{i}" for i in range(1, 9))


def across_sql(keys, judges, names=STRATEGIES) -> str:
    """by_strategy() over several workloads."""
    return " union all ".join(f"select * from ({derive_sql(k)}{by_strategy_sql(k, judges, names)}) m{i}" for i, k in enumerate(keys))


@query("metric_mean_f1", f"select judge, strategy, count(*) as workloads, round(avg(f1), 4) as mean_f1 from ({across_sql(MEAN, [LENIENT])}) a group by judge, strategy")
def _(s, d):
    return each(s, d, MEAN, lambda k: by_strategy(s, d, [k], [LENIENT])).groupBy("judge", "strategy").agg(F.count(F.lit(1)).alias("workloads"), F.round(F.avg("f1"), 4).alias("mean_f1"))
