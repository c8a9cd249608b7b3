"""One candidate table a workload: sampled anchors, their candidates, similarities, truth. Every strategy reads the same."""

from __future__ import annotations

import gc
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from recmatch.functions.similarity import overall, similarity
from recmatch.plans.blocking import block_tfidf, blocking_sql, over_cores, token_lists
from recmatch.plans.overlap import passing, similar
from recmatch.plans.workloads import GRAMS, WORD_HASHES, WORKLOADS, Workload, dialect
from recmatch.sources.tables import plain, sql, table

MATCHED, UNMATCHED, LIST = 300, 100, 10
_kept: dict[tuple, DataFrame] = {}
#: Small workloads at once. With eight, plans and broadcasts took more than 1500 MB of the driver's memory.
AT_ONCE = 2
#: Bytes of all tables below which shuffles of two workloads and token lists may lie on disk together.
SMALL = 64 << 20
#: The tables that workloads are made of.
READ = ("customer", "supplier", "part", "orders", "lineitem", "documents", "pages", "benchmark")


def shared(spark: SparkSession) -> str:
    sc = spark.sparkContext
    where = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not where:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        where = "file:///tmp/recmatch-shared"
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(where)
    return where if ":/" in where else f"file://{where}"


def kept(spark: SparkSession, key: tuple, make) -> DataFrame:
    """A table written once a session in the shared folder."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _kept:
        path = f"{shared(spark).rstrip('/')}/{'-'.join(str(k).replace('/', '_').replace(':', '_') for k in key[2:])[-60:]}-{uuid.uuid4().hex[:8]}"
        df = make()
        df.write.parquet(path)
        _kept[key] = spark.read.schema(df.schema).parquet(path)
        del df
        gc.collect()
        spark.sparkContext._jvm.System.gc()  # Spark deletes the shuffles that nobody can read
    return _kept[key]


def small(spark: SparkSession, sf_dir: str) -> bool:
    return sum(int(str(table(spark, sf_dir, n)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) for n in READ) < SMALL


def together(spark: SparkSession, sf_dir: str, keys, make) -> list:
    """make(key) of each workload, in the order of keys.

    Small tables keep few tasks busy, so AT_ONCE of their workloads go at once; large ones go one after another, and no two have shuffles on disk.
    """
    if not small(spark, sf_dir):
        return [make(k) for k in keys]
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return [f.result() for f in [pool.submit(inheritable_thread_target(spark)(make), k) for k in keys]]  # a copy of the session's properties each


def each(spark: SparkSession, sf_dir: str, keys, rates) -> DataFrame:
    """The few rows of rates(key) of each workload: one small plan a workload instead of one that holds all."""

    def rows(key):
        df = rates(key)
        return df.schema, df.collect()

    parts = together(spark, sf_dir, keys, rows)
    return spark.createDataFrame([r for _, p in parts for r in p], parts[0][0])


def side(spark: SparkSession, sf_dir: str, w: Workload, which: str) -> DataFrame:
    text = dialect(getattr(w, which), "spark")
    if which != "truth" or "{documents" not in text:
        return sql(spark, sf_dir, text)
    docs = over_cores(table(spark, sf_dir, "documents"))
    if "{documents_grams}" not in text:
        return sql(spark, sf_dir, text, documents=docs)
    # 64-bit hashes of the grams meet: a collision within a pair of documents would count as a shared gram.
    grams = sql(spark, sf_dir, GRAMS["spark"], documents=docs).withColumn("gram", F.xxhash64("gram"))
    return sql(spark, sf_dir, text, documents_grams=grams)


def word_hashes(spark: SparkSession, sf_dir: str) -> DataFrame | None:
    """rid, w of the documents that have an id, or None if two have the same: grams of both would count as one document's."""
    docs = table(spark, sf_dir, "documents").filter("doc_id is not null")
    if docs.groupBy("doc_id").count().filter("count > 1").isEmpty():
        return over_cores(docs).select(F.col("doc_id").cast("long").alias("rid"), F.expr(WORD_HASHES).alias("w"))


def truth(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """anchor_id, cand_id of true matches, stored. Documents that share grams meet by prefixes of their sets, whose postings take less disk than all grams."""
    w = WORKLOADS[key]

    def make():
        docs = word_hashes(spark, sf_dir) if w.overlap else None
        if docs is None:
            return side(spark, sf_dir, w, "truth")
        ends = docs.filter("rid % 2 in (0, 1)").select("rid", F.expr("rid % 2 = 0").alias("a"), F.expr("rid % 2 = 1").alias("b"), "w")
        return similar(ends, w.overlap, store).select(F.col("x").alias("anchor_id"), F.col("y").alias("cand_id"))

    with passing(spark, shared(spark)) as store:
        return kept(spark, (sf_dir, key, "truth"), make)


def sample(d1: DataFrame, true: DataFrame, matched: int = MATCHED, unmatched: int = UNMATCHED, seed: str = "s") -> DataFrame:
    """rid, is_matched of the evaluation anchors: the first of either kind in the order of a digest, three quarters of a kind at most; the rest is for training."""
    flagged = d1.select("rid").join(true.select(F.col("anchor_id").alias("rid"), F.lit(True).alias("m")).distinct(), "rid", "left").select("rid", F.coalesce("m", F.lit(False)).alias("is_matched"))
    order = Window.partitionBy("is_matched").orderBy(F.md5(F.concat(F.lit(f"{seed}|"), F.col("rid").cast("string"))), "rid")
    most = F.least(F.when(F.col("is_matched"), matched).otherwise(unmatched), F.ceil(0.75 * F.col("of")))
    counts = flagged.groupBy("is_matched").agg(F.count(F.lit(1)).alias("of"))  # two rows
    return flagged.withColumn("n", F.row_number().over(order)).join(F.broadcast(counts), "is_matched").filter(F.col("n") <= most).select("rid", "is_matched")


def compared(pairs: DataFrame, d1: DataFrame, d2: DataFrame, w: Workload) -> DataFrame:
    """pairs with an s_<attribute> each and the overall sim. Attributes join late, to ids that blocking kept.

    Pairs of a bounded set of anchors fit few partitions of a shuffle, but comparing texts takes long: they go to all cores.
    """
    a = d1.select(F.col("rid").alias("anchor_id"), *(F.col(t.name).alias(f"a_{t.name}") for t in w.attributes))
    b = d2.select(F.col("rid").alias("cand_id"), *(F.col(t.name).alias(f"b_{t.name}") for t in w.attributes))
    both = pairs.join(a, "anchor_id").join(b, "cand_id").repartition(pairs.sparkSession.sparkContext.defaultParallelism)
    both = both.select(*pairs.columns, *(F.expr(similarity(t, f"a_{t.name}", f"b_{t.name}", "spark")).cast("double").alias(f"s_{t.name}") for t in w.attributes))
    return both.withColumn("sim", F.expr(overall(w, "spark"))).withColumns({f"s_{t.name}": F.round(f"s_{t.name}", 6) for t in w.attributes})


def records(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """The second side. If it takes joins, it is stored: blocking and comparing read it several times, and each would deal out all its attributes."""
    d2 = side(spark, sf_dir, WORKLOADS[key], "d2")
    return kept(spark, (sf_dir, key, "d2"), lambda: d2) if " join " in WORKLOADS[key].d2 else d2


def tokens(spark: SparkSession, sf_dir: str, key: str) -> DataFrame | None:
    """The second side's token lists, stored: blocking reads them twice for each set of anchors. Large ones are made again instead, which takes no disk."""
    if small(spark, sf_dir):
        return kept(spark, (sf_dir, key, "tokens"), lambda: token_lists(records(spark, sf_dir, key), WORKLOADS[key]))


def anchors(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """The evaluation anchors' records, stored: MATCHED + UNMATCHED rows at most, few enough to broadcast."""
    d1, true = side(spark, sf_dir, WORKLOADS[key], "d1"), truth(spark, sf_dir, key)
    return kept(spark, (sf_dir, key, "anchors"), lambda: d1.join(F.broadcast(sample(d1, true)), "rid", "left_semi"))


def candidates(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """anchor_id, cand_id, pos, block_score, s_*, sim, is_true of a workload's evaluation anchors."""

    def make():
        w, true = WORKLOADS[key], truth(spark, sf_dir, key)
        picked, d2 = anchors(spark, sf_dir, key), records(spark, sf_dir, key)
        pairs = kept(spark, (sf_dir, key, "pairs"), lambda: block_tfidf(picked, d2, w, LIST, lists=tokens(spark, sf_dir, key)))
        # Broadcast: candidates of the anchors, LIST times as many.
        few = d2.join(F.broadcast(pairs.select(F.col("cand_id").alias("rid")).distinct()), "rid", "left_semi")
        scored = compared(pairs, picked, few, w)
        return scored.join(true.withColumn("t", F.lit(True)), ["anchor_id", "cand_id"], "left").withColumn("is_true", F.coalesce("t", F.lit(False))).drop("t")

    return kept(spark, (sf_dir, key, "candidates"), make)


def nested(cands: DataFrame, *more: str) -> DataFrame:
    """One row an anchor: cands, an array by position. Lists are as long as blocking made them."""
    return cands.groupBy("anchor_id").agg(F.array_sort(F.collect_list(F.struct("pos", "cand_id", "sim", "is_true", *more))).alias("cands"))


def derive_sql(key: str, sampled: bool = True, n: int = LIST) -> str:
    """Oracle: common table expressions ending in cs, the counterpart of candidates()."""
    w = WORKLOADS[key]
    text = {k: plain(dialect(getattr(w, k), "oracle")).replace("as string)", "as varchar)") for k in ("d1", "d2", "truth")}
    grams = f"documents_grams as ({GRAMS['oracle']}), " if "documents_grams" in text["truth"] else ""
    sims = ", ".join(f"cast({similarity(t, f'a.{t.name}', f'b.{t.name}', 'oracle')} as double) as s_{t.name}" for t in w.attributes)
    rounded = ", ".join(f"round(s_{t.name}, 6) as s_{t.name}" for t in w.attributes)
    pick = f"""picked as (select d1.* from d1 join (select rid, row_number() over (partition by m order by md5(concat('s|', cast(rid as varchar))), rid) as k, ceil(0.75 * count(*) over (partition by m)) as most, m
 from (select rid, rid in (select anchor_id from truth) as m from d1)) q on d1.rid = q.rid where k <= least(most, case when m then {MATCHED} else {UNMATCHED} end)), """
    return f"""with {grams}d1 as ({text['d1']}), d2 as ({text['d2']}), truth as ({text['truth']}), {pick if sampled else ''}
 {blocking_sql(w, 'picked' if sampled else 'd1', n)},
 cmp as (select c.anchor_id, c.cand_id, c.pos, c.block_score, {sims} from cand c join {'picked' if sampled else 'd1'} a on a.rid = c.anchor_id join d2 b on b.rid = c.cand_id),
 cs as (select anchor_id, cand_id, pos, block_score, {rounded}, {overall(w, 'oracle')} as sim, exists (select 1 from truth t where t.anchor_id = cmp.anchor_id and t.cand_id = cmp.cand_id) as is_true from cmp)
"""
