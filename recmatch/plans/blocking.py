"""Blocking: short ranked candidate lists. Token-index search, its saturating form, exact keys, MinHash bands, vectors, brute force."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from recmatch.functions.similarity import qgrams, words
from recmatch.plans.overlap import similar
from recmatch.plans.workloads import Workload


def text_of(w: Workload, prefix: str = "") -> str:
    return "concat_ws(' ', " + ", ".join(f"cast({prefix}{c} as string)" for c in w.blocked_on) + ")"


def tokens_of(w: Workload, name: str) -> str:
    return (words if w.tokens == "word" else qgrams)(text_of(w), name)


def token_table(records: DataFrame, w: Workload) -> DataFrame:
    return records.select("rid", F.explode(F.expr(tokens_of(w, "spark"))).alias("tok"))


def top_n(scored: DataFrame, n: int) -> DataFrame:
    """(anchor_id, cand_id, pos, block_score): Spark limits each group before the exchange's full sort."""
    best = Window.partitionBy("anchor_id").orderBy(F.desc("block_score"), "cand_id")
    return scored.withColumn("pos", F.row_number().over(best)).filter(F.col("pos") <= n).select("anchor_id", "cand_id", "pos", "block_score")


#: Anchors scored in one pass over the records, records scored at once, and the size below which records are spread over all cores.
PASS, ROWS, SMALL = 2000, 2048, 256 << 20


def over_cores(records: DataFrame) -> DataFrame:
    """Few records, as in one file, go to all cores before something is done with their texts. A file for each core is enough."""
    cores = records.sparkSession.sparkContext.defaultParallelism
    if int(str(records._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) < SMALL and len(records.inputFiles()) < cores:
        records = records.repartition(cores)
    return records


def token_lists(records: DataFrame, w: Workload) -> DataFrame:
    """rid, toks."""
    return over_cores(records).select("rid", F.expr(tokens_of(w, "spark")).alias("toks"))


class Best:
    """The n best (score, smaller id) of each of so many anchors."""

    def __init__(self, anchors: int, n: int):
        import numpy as np

        self.n, self.least = n, np.zeros(anchors)
        self.anchor, self.rid, self.score = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)

    def add(self, anchor, rid, score) -> None:
        import numpy as np

        a, r, s = np.concatenate([self.anchor, anchor]), np.concatenate([self.rid, rid]), np.concatenate([self.score, score])
        o = np.lexsort((r, -s, a))
        a, r, s = a[o], r[o], s[o]
        place = np.arange(len(a)) - np.searchsorted(a, a)
        top = place < self.n
        self.anchor, self.rid, self.score = a[top], r[top], s[top]
        full = place == self.n - 1
        self.least[a[full]] = s[full]


def scored_in_place(lists: DataFrame, asked, n: int, exclude_self: bool) -> DataFrame:
    """anchor_id, cand_id, block_score: of each task's records the n best of each anchor, so that no pairs but these leave the task.

    asked: anchor_id, tok, weight of a bounded set of anchors, as Arrow. Damped lists carry a factor, damp.
    """
    import numpy as np
    import pyarrow as pa

    ids, at = np.unique(asked["anchor_id"].to_numpy(), return_inverse=True)
    toks = asked["tok"].unique()
    damped = "damp" in lists.columns

    def score(batches):
        import pyarrow.compute as pc

        tok = pc.index_in(asked["tok"], value_set=toks).to_numpy()
        order = np.argsort(tok, kind="stable")
        starts = np.searchsorted(tok[order], np.arange(len(toks) + 1))
        who, weight = at[order], asked["weight"].to_numpy()[order]
        some = bool((weight == 0).any())
        best = Best(len(ids), n)
        for whole in batches:
            for lo in range(0, whole.num_rows, ROWS):
                batch = whole.slice(lo, ROWS)
                rid, lst = batch.column("rid").to_numpy(), batch.column("toks")
                row, hit = pc.list_parent_indices(lst).to_numpy(), pc.index_in(pc.list_flatten(lst), value_set=toks)
                row, hit = row[pc.is_valid(hit).to_numpy(zero_copy_only=False)], pc.drop_null(hit).to_numpy()
                by = np.argsort(hit, kind="stable")
                row, hit = row[by], hit[by]
                sums = np.zeros((batch.num_rows, len(ids)))
                met = np.zeros(sums.shape, bool) if some else None
                found, cuts = np.unique(hit, return_index=True)
                for t, x, y in zip(found, cuts, [*cuts[1:], len(hit)]):
                    rows, mine = row[x:y, None], slice(starts[t], starts[t + 1])
                    sums[rows, who[mine]] += weight[mine]
                    if some:
                        met[rows, who[mine]] = True
                if damped:
                    sums *= batch.column("damp").to_numpy()[:, None]
                high = (met if some else sums > 0) & (sums >= best.least - 1e-6)
                if exclude_self:
                    high &= rid[:, None] != ids
                i, a = np.nonzero(high)
                best.add(a, rid[i], np.round(sums[i, a], 6))
        yield pa.RecordBatch.from_arrays([pa.array(ids[best.anchor]), pa.array(best.rid), pa.array(best.score)], names=["anchor_id", "cand_id", "block_score"])

    return lists.mapInArrow(score, "anchor_id long, cand_id long, block_score double")


def block_tfidf(d1: DataFrame, d2: DataFrame, w: Workload, n: int = 10, exclude_self: bool = False, saturated: tuple[float, float] | None = None, lists: DataFrame | None = None) -> DataFrame:
    """Candidates by the sum of log(N / df) over shared tokens; tokens of more than max_df * N records are no evidence.

    saturated: (k1, b) weighs each token by the record's length instead, as token counts here are 0 or 1. d1 is a bounded set (a sample,
    training anchors, items of a batch): its tokens go to all tasks, PASS anchors at a time, and records are scored where they are read.
    lists: token_lists of d2, if somebody has them.
    """
    lists = token_lists(d2, w) if lists is None else lists
    index = lists.select("rid", F.explode("toks").alias("tok"))
    total = d2.agg(F.count(F.lit(1)).alias("total"))
    df = index.groupBy("tok").agg(F.count(F.lit(1)).alias("df")).join(F.broadcast(total)).filter(F.col("df") <= w.max_df * F.col("total"))  # one row
    if saturated:
        k1, b = saturated
        mean = lists.filter(F.size("toks") > 0).agg(F.avg(F.size("toks")).alias("mean"))
        lists = lists.join(F.broadcast(mean)).select("rid", "toks", (F.lit(k1 + 1) / (1 + k1 * (1 - b + b * F.size("toks") / F.col("mean")))).alias("damp"))
    asked = token_table(d1, w).join(df, "tok").select(F.col("rid").cast("long").alias("anchor_id"), "tok", F.log(F.col("total") / F.col("df")).alias("weight"))
    asked = asked.toArrow().combine_chunks().sort_by("anchor_id")
    return top_n(in_passes(lists, asked, n, exclude_self), n)


def in_passes(lists: DataFrame, asked, n: int, exclude_self: bool) -> DataFrame:
    import numpy as np

    ids = np.unique(asked["anchor_id"].to_numpy())
    ends = np.searchsorted(asked["anchor_id"].to_numpy(), ids[::PASS]).tolist() + [asked.num_rows]
    out = None
    for lo, hi in zip(ends, ends[1:]):
        part = scored_in_place(lists, asked.slice(lo, hi - lo), n, exclude_self)
        out = part if out is None else out.unionAll(part)
    return lists.sparkSession.createDataFrame([], "anchor_id long, cand_id long, block_score double") if out is None else out


def block_same(records: DataFrame, w: Workload, n: int, keep) -> DataFrame:
    """block_tfidf of a collection with itself, a record apart from itself, for any number of records: only different token sets meet.

    The n + 1 best sets of a set, by score and smallest id, hold its records' n best candidates, among the n + 1 smallest ids of each.
    keep(name, make) stores a table.
    """
    by = Window.partitionBy("toks")
    made = lambda: token_lists(records, w).select("rid", F.array_sort("toks").alias("toks")).withColumn("cls", F.min("rid").over(by)).withColumn("place", F.row_number().over(by.orderBy("rid")))
    lists = keep("sets", made)
    classes = lists.filter("place = 1").select("rid", "toks")
    total = lists.agg(F.count(F.lit(1)).alias("total"))
    sizes = lists.groupBy("cls").agg(F.count(F.lit(1)).alias("size")).withColumnRenamed("cls", "rid")
    index = classes.join(sizes, "rid").select("rid", "size", F.explode("toks").alias("tok"))
    df = index.groupBy("tok").agg(F.sum("size").alias("df")).join(F.broadcast(total)).filter(F.col("df") <= w.max_df * F.col("total"))  # one row
    asked = index.join(df, "tok").select(F.col("rid").cast("long").alias("anchor_id"), "tok", F.log(F.col("total") / F.col("df")).alias("weight"))
    near = keep("near", lambda: top_n(in_passes(classes, asked.toArrow().combine_chunks().sort_by("anchor_id"), n + 1, False), n + 1).drop("pos"))
    few = lists.filter(F.col("place") <= n + 1).select(F.col("cls").alias("cand_cls"), F.col("rid").alias("cand_id"))
    reach = near.select(F.col("anchor_id").alias("cls"), F.col("cand_id").alias("cand_cls"), "block_score").join(few, "cand_cls")
    reach = reach.withColumn("pos", F.row_number().over(Window.partitionBy("cls").orderBy(F.desc("block_score"), "cand_id"))).filter(F.col("pos") <= n + 1)
    pairs = lists.select(F.col("rid").alias("anchor_id"), "cls").join(reach, "cls").filter("anchor_id <> cand_id")
    return top_n(pairs.select("anchor_id", "cand_id", "block_score"), n)


def block_key(d1: DataFrame, d2: DataFrame, keys: list[str]) -> DataFrame:
    """All pairs that agree on the keys."""
    return d1.select(F.col("rid").alias("anchor_id"), *keys).join(d2.select(F.col("rid").alias("cand_id"), *keys), keys).select("anchor_id", "cand_id")


def nearest(vectors: DataFrame, ids, asked, n: int, planes=None, reach: int = 0) -> DataFrame:
    """anchor_id, cand_id, block_score: of each task's vectors (rid, v) the n of best cosine for each of the vectors asked, one a row.

    planes: normals of hyperplanes, one a row; only vectors whose signs differ from an anchor's in at most reach are compared with it.
    Vectors of length 0 have no cosine and come last, without one.
    """
    import numpy as np
    import pyarrow as pa

    def units(m):
        length = np.sqrt((m * m).sum(1, keepdims=True))
        return np.divide(m, length, out=np.zeros_like(m), where=length > 0), length[:, 0] > 0

    def codes(m):
        return ((m @ planes.T > 0) << np.arange(len(planes))).sum(1)

    def score(batches):
        best = Best(len(ids), n)
        best.least[:] = -np.inf
        mine, known = units(asked)
        wanted = codes(asked) if planes is not None else None
        for whole in batches:
            for lo in range(0, whole.num_rows, ROWS):
                batch = whole.slice(lo, ROWS)
                rid, lst = batch.column("rid").to_numpy(), batch.column("v")
                v = lst.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(rid), -1)
                unit, real = units(v)
                code = codes(v) if planes is not None else np.zeros(len(rid), np.int64)
                for c in np.unique(code):
                    rows = np.flatnonzero(code == c)
                    who = np.arange(len(ids)) if planes is None else np.flatnonzero(np.bitwise_count(wanted ^ c) <= reach)
                    sims = mine[who] @ unit[rows].T
                    sims[~known[who]] = sims[:, ~real[rows]] = -np.inf
                    least = best.least[who]
                    if len(rows) > n and np.isneginf(least).any():
                        least = np.maximum(least, np.partition(sims, -n, axis=1)[:, -n])
                    i, j = np.nonzero(sims >= least[:, None] - 1e-6)
                    best.add(who[i], rid[rows[j]], np.round(sims[i, j], 6))
        yield pa.RecordBatch.from_arrays([pa.array(ids[best.anchor]), pa.array(best.rid), pa.array(best.score)], names=["anchor_id", "cand_id", "block_score"])

    return vectors.mapInArrow(score, "anchor_id long, cand_id long, block_score double")


def block_vectors(d1: DataFrame, d2: DataFrame, n: int = 10, planes: int = 0, seed: int = 5, reach: int = 1) -> DataFrame:
    """Nearest vectors (rid, v) by cosine. planes: > 0 compares within buckets of random-hyperplane signs that differ in at most reach.

    d1 is a bounded set of query vectors: they go to all tasks, PASS at a time, and vectors are scored where they are read. Null vectors
    are no candidates and have none.
    """
    import numpy as np

    asked = d1.filter("v is not null").select(F.col("rid").cast("long").alias("rid"), "v").toArrow().combine_chunks().sort_by("rid")
    vectors = d2.filter("v is not null").select(F.col("rid").cast("long").alias("rid"), "v")
    ids = asked["rid"].to_numpy()
    rows = asked["v"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(ids), -1) if len(ids) else None
    normals = np.random.default_rng(seed).normal(size=(planes, rows.shape[1])) if planes and len(ids) else None
    out = None
    for lo in range(0, len(ids), PASS):
        part = nearest(vectors, ids[lo : lo + PASS], rows[lo : lo + PASS], n, normals, reach)
        out = part if out is None else out.unionAll(part)
    if out is None:
        out = d2.sparkSession.createDataFrame([], "anchor_id long, cand_id long, block_score double")
    return top_n(out, n).withColumn("block_score", F.when(F.col("block_score") >= -1.5, F.col("block_score")))


def block_minhash(d1: DataFrame, d2: DataFrame, bands: int = 20, rows: int = 4, least: float = 0.4) -> DataFrame:
    """Pairs of records (rid, grams) that share a band of MinHash values and reach the least Jaccard, exactly verified."""
    n = bands * rows

    def keyed(d: DataFrame) -> DataFrame:
        """rid, band: values as one aggregate over exploded grams, which compiles; higher-order functions would not."""
        mins = d.select("rid", F.explode("grams").alias("g")).groupBy("rid").agg(*(F.min(F.xxhash64(F.lit(i), "g")).alias(f"m{i}") for i in range(n)))
        return mins.select("rid", F.explode(F.array(*(F.xxhash64(F.lit(b), *(F.col(f"m{b * rows + r}") for r in range(rows))) for b in range(bands)))).alias("band"))

    pairs = keyed(d1).select(F.col("rid").alias("anchor_id"), "band").join(keyed(d2).select(F.col("rid").alias("cand_id"), "band"), "band").filter("anchor_id <> cand_id").select("anchor_id", "cand_id").distinct()
    both = pairs.join(d1.select(F.col("rid").alias("anchor_id"), F.col("grams").alias("x")), "anchor_id").join(d2.select(F.col("rid").alias("cand_id"), F.col("grams").alias("y")), "cand_id")
    j = F.size(F.array_intersect("x", "y")) / F.size(F.array_union("x", "y"))
    return both.select("anchor_id", "cand_id", F.round(j, 6).alias("block_score")).filter(F.col("block_score") >= least)


def block_minhash_words(docs: DataFrame, store, bands: int = 20, rows: int = 4, least: float = 0.4) -> DataFrame:
    """block_minhash of records (rid, w), their words as hashes, with themselves. Equal sets meet once, and no grams are stored or sent with each pair."""
    both = docs.withColumns({"a": F.lit(True), "b": F.lit(True)})
    found = similar(both, round(100 * least), store, (bands, rows))
    return found.select(F.col("x").alias("anchor_id"), F.col("y").alias("cand_id"), F.round("share", 6).alias("block_score"))


def blocking_sql(w: Workload, anchors: str = "d1", n: int = 10, exclude_self: bool = False, saturated: tuple[float, float] | None = None) -> str:
    """Oracle of block_tfidf: common table expressions over d1 and d2, ending in cand."""
    tok = tokens_of(w, "oracle")
    damp, extra = "", ""
    if saturated:
        k1, b = saturated
        extra = f", lens as (select rid, count(*) as len from idx group by rid), damps as (select rid, {k1 + 1}e0 / (1 + {k1}e0 * (1 - {b}e0 + {b}e0 * len / (select avg(len) from lens))) as damp from lens)"
        damp = " * (select damp from damps where damps.rid = idx.rid)"
    return f"""idx as (select distinct rid, unnest({tok}) as tok from d2), tot as (select count(*) as total from d2),
 dfs as (select tok, count(*) as df from idx group by tok having count(*) <= {w.max_df}e0 * (select total from tot)){extra},
 post as (select tok, rid as cand_id, ln(cast((select total from tot) as double) / df){damp} as weight from idx join dfs using (tok)),
 ask as (select distinct rid as anchor_id, unnest({tok}) as tok from {anchors}),
 scored as (select anchor_id, cand_id, round(sum(weight), 6) as block_score from ask join post using (tok) {'where anchor_id <> cand_id' if exclude_self else ''} group by anchor_id, cand_id),
 cand as (select anchor_id, cand_id, pos, block_score from (select *, cast(row_number() over (partition by anchor_id order by block_score desc, cand_id) as integer) as pos from scored) where pos <= {n})"""
