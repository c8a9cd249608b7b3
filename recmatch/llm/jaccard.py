"""Jaccard self-join on word n-grams with adaptive multi-match prefixes.

Every document's distinct shingles are put in one order of the whole corpus, rare before frequent. If two
documents are similar enough, the prefixes that are l shingles longer than what the threshold lets them
differ by share at least l shingles. l is chosen per document: the postings a longer prefix adds are
weighed against the candidates that the stricter count saves. A pair of documents with l and l' needs
min(l, l') common prefix shingles, and enough of them that the rest could still reach the threshold; then
it is verified exactly on whole shingle sets.

Equal sets are one class and are joined once. Groups of near copies are not expanded into pairs: stars verify
the members of a posting list against two members only, and link what passes. Then all pairs across components are tried: those of short lists as rows, those of long lists in
blocks of documents that meet in a task. This last step alone loses no link between components; the stars
only save work.

Result: n_shingles, the component's smallest doc_id, for every row. Null, empty and wordless texts: 0
shingles, no links. Rows that share a doc_id are one node of the graph. Null ids are not linked; their
component is null. Texts shorter than a shingle have one, of all their words.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_up, documents, numbered, settled, stored, tidy, without
from .components import components
from .shingles import Words, mix, shingled, slices

#: Shingles counted together when looking for frequent ones; how many of these are ordered by count at most; bits of a filter.
CHUNK, FREQUENT, BITS = 1 << 21, 1 << 18, 26
MOST_MATCHES, VERIFY_COST = 4, 0.05
#: Lists of more documents go to blocks; documents a block and shingles a block, on average.
SHORT, BLOCK, WEIGHT = 16, 384, 1 << 19


@dataclass(frozen=True)
class Rule:
    """Shingles of `words` words; a link where 100 * intersection >= percent * union."""

    words: int = 4
    percent: int = 85

    def least_overlap(self, n: int) -> int:
        return -(-self.percent * n // 100)


def sets(b: pa.RecordBatch, column: int, tool: Words, words: int):
    """(row, sorted distinct shingle hashes) of each row of a batch."""
    for data, off, row in slices(b.column(column)):
        h, first = tool.of(data, off)
        s, ptr = shingled(h, first, words)
        for i in range(len(off) - 1):
            own = np.sort(s[ptr[i] : ptr[i + 1]])
            yield row + i, own[np.concatenate([[True], own[1:] != own[:-1]])] if len(own) else own


def profiles(docs: DataFrame, rule: Rule) -> tuple[DataFrame, DataFrame]:
    """(id, n, sig) of every row, and counts (h, n) of shingles that some chunk holds twice or more.

    A shingle's sum over chunks is a lower bound of its document frequency, and is there for every shingle of
    more documents than there are chunks. It serves the order only, which may be any.
    """

    def run(batches):
        tool, have, size, seen = Words("blank"), [], 0, set()

        def frequent():
            h, n = np.unique(np.concatenate(have), return_counts=True) if have else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
            return h[n > 1].view(np.int64), n[n > 1]

        def out(ids, n, sig, h, c):
            rest = [None] * len(h)
            return pa.RecordBatch.from_arrays([pa.array([*ids, *rest], pa.int64()), pa.array([*n, *rest], pa.int64()), pa.array([*sig, *rest], pa.binary()), pa.array([*[None] * len(ids), *h.tolist()], pa.int64()), pa.array([*[None] * len(ids), *c.tolist()], pa.int64())], names=["id", "n", "sig", "h", "c"])

        empty = np.zeros(0, np.int64)
        for b in batches:
            n, sig = [], []
            for _, own in sets(b, 1, tool, rule.words):
                n.append(len(own))
                sig.append(hashlib.blake2b(own.tobytes(), digest_size=16).digest())
                if sig[-1] not in seen and len(own):
                    seen.add(sig[-1])
                    have.append(own)
                    size += len(own)
            yield out(b.column(0).to_pylist(), n, sig, empty, empty)
            if size >= CHUNK:
                h, c = frequent()
                have, size, seen = [], 0, set()
                yield out([], [], [], h, c)
        h, c = frequent()
        yield out([], [], [], h, c)

    both = stored(docs.mapInArrow(tidy(run), "id long, n long, sig binary, h long, c long"), "profiles")
    return both.filter("sig is not null").select("id", "n", "sig"), both.filter("h is not null").select("h", "c")


def bitmap(places: DataFrame, bits: int = BITS) -> bytes:
    """A filter of fixed size of a one-column table of places below 2**bits; never misses one. At most 2**(bits - 6) rows reach the driver."""
    p = F.col(places.columns[0])
    words = places.groupBy(F.shiftright(p, 6).cast("int").alias("at")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(`{places.columns[0]}` % 64 as int))")).alias("v"))
    out = np.zeros(2 ** (bits - 6), np.int64)
    for part in words.toArrow().to_batches():
        out[part.column(0).to_numpy()] = part.column(1).to_numpy()
    return out.tobytes()


def place(column: str = "id"):
    return F.pmod(F.xxhash64(column), F.lit(2**BITS))


def among(bits: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Which places a filter holds."""
    return (bits[p >> 6] >> (p & 63) & 1).astype(bool)


def only(docs: DataFrame, ids: DataFrame, run, schema: str, inside: bool = True) -> DataFrame:
    """run over the rows of docs (id, ...) whose id may be among ids, or with `inside` false over all others, in one Python step."""
    sent = docs.sparkSession.sparkContext.broadcast(bitmap(ids.select(place(ids.columns[0]).alias("p"))))

    def picked(batches):
        bits = np.frombuffer(sent.value, np.int64)
        for b in batches:
            yield b.filter(pa.array(among(bits, b.column(b.num_columns - 1).to_numpy()) == inside))

    return docs.withColumn("_place", place()).mapInArrow(tidy(lambda batches: run(picked(batches))), schema)


def filtered(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows of docs (id, ...) whose id may be among ids; a cheap narrow step before a join."""
    return only(docs, ids, lambda batches: batches, docs.withColumn("_place", place()).schema).drop("_place")


def prefix(own: np.ndarray, order: np.ndarray, df: np.ndarray, rule: Rule) -> tuple[np.ndarray, int]:
    """The prefix of a set under the order, and its l, by estimated cost.

    With l matches, a candidate stands in l of the prefix's postings, so also in one outside any l - 1 of them: the
    candidates are at most the postings' sum less its l - 1 largest lists.
    """
    n = len(own)
    base = n - rule.least_overlap(n)
    best, choice = None, 1
    others = df[order] - 1
    if not others[: base + 1].any():
        return own[order[: base + 1]], 1
    for m in range(1, min(MOST_MATCHES, n - base) + 1):
        post = others[: base + m]
        top = np.sort(post)[len(post) - (m - 1) :].sum() if m > 1 else 0
        cost = len(post) + post.sum() + VERIFY_COST * n * (post.sum() - top)
        if best is None or cost < best:
            best, choice = cost, m
    return own[order[: base + choice]], choice


def prefixes(docs: DataFrame, ids: DataFrame, frequent: DataFrame, rule: Rule) -> DataFrame:
    """id, n, p (prefix length), l, tokens of the documents that may be in ids."""
    spark = docs.sparkSession
    top = frequent.groupBy("h").agg(F.sum("c").alias("c")).filter("c >= 4").orderBy(F.desc("c"), "h").limit(FREQUENT).toArrow()
    h, c = top.column("h").to_numpy().view(np.uint64), top.column("c").to_numpy()
    at = np.argsort(h)
    sent = spark.sparkContext.broadcast((h[at].tobytes(), c[at].astype(np.int64).tobytes()))

    def run(batches):
        known, count = (np.frombuffer(x, t) for x, t in zip(sent.value, (np.uint64, np.int64)))
        maybe = np.zeros(1 << 22, bool)
        maybe[(known & np.uint64(2**22 - 1)).astype(np.int64)] = True
        tool, seen = Words("blank"), set()
        for b in batches:
            ids, tokens, n, p, m = [], [], [], [], []
            for r, own in sets(b, 1, tool, rule.words):
                i = b.column(0)[r].as_py()
                if not len(own) or i is None:
                    continue
                sig = hashlib.blake2b(own.tobytes(), digest_size=16).digest()
                if (sig, i) in seen:
                    continue
                seen.add((sig, i))
                df = np.ones(len(own), np.int64)
                hit = np.flatnonzero(maybe[(own & np.uint64(2**22 - 1)).astype(np.int64)]) if len(known) else ()
                if len(hit):
                    k = np.minimum(np.searchsorted(known, own[hit]), len(known) - 1)
                    same = known[k] == own[hit]
                    df[hit[same]] = count[k[same]]
                order = np.argsort(np.log2(df).astype(np.int8), kind="stable")
                some, choice = prefix(own, order, df, rule)
                ids.append(i)
                tokens.append(some.view(np.int64))
                n.append(len(own))
                p.append(len(some))
                m.append(choice)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(p)]).astype(np.int32) if p else [0], pa.int32()), pa.array(np.concatenate(tokens) if tokens else [], pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(n, pa.int32()), pa.array(p, pa.int32()), pa.array(m, pa.int32()), lists], names=["id", "n", "p", "l", "tokens"])

    return only(docs, ids, run, "id long, n int, p int, l int, tokens array<long>")


def postings(pre: DataFrame) -> DataFrame:
    """(token, id) of prefix shingles that two documents and more hold; most stand in one, and go before any join."""
    again = stored(pre.select(F.explode("tokens").alias("token")).groupBy("token").count().filter("count > 1").select("token"), "tokens")
    low = 2**BITS - 1
    sent = pre.sparkSession.sparkContext.broadcast(bitmap(again.select(F.col("token").bitwiseAND(low).alias("p"))))

    def run(batches):
        bits = np.frombuffer(sent.value, np.int64)
        for b in batches:
            tokens = b.column(1).flatten().to_numpy(zero_copy_only=False)
            ids = np.repeat(b.column(0).to_numpy(zero_copy_only=False), b.column(1).value_lengths().to_numpy(zero_copy_only=False))
            keep = among(bits, tokens & low)
            yield pa.RecordBatch.from_arrays([pa.array(tokens[keep], pa.int64()), pa.array(ids[keep], pa.int64())], names=["token", "id"])

    return stored(pre.select("id", "tokens").mapInArrow(tidy(run), "token long, id long").join(again, "token", "left_semi").distinct(), "lists")


def packed(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """(id, z), compressed texts, of the documents in ids (id); only these are shuffled."""

    def pack(batches):
        import zstandard

        tool = zstandard.ZstdCompressor(level=1)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([tool.compress((t or "").encode("utf-8", "surrogatepass")) for t in b.column(1).to_pylist()], pa.binary())], names=["id", "z"])

    return stored(only(docs, ids, pack, "id long, z binary").distinct().join(ids, "id", "left_semi"), "bodies")


def unpacked(z: list, rule: Rule) -> dict:
    """Shingle sets by compressed text."""
    import zstandard

    tool, unique = zstandard.ZstdDecompressor(), list(dict.fromkeys(z))
    texts = pa.RecordBatch.from_arrays([pa.array([tool.decompress(x) for x in unique], pa.binary()).cast(pa.string())], names=["text"])
    return dict(zip(unique, (s for _, s in sets(texts, 0, Words("blank"), rule.words))))


def verify(docs: DataFrame, pairs: DataFrame, rule: Rule) -> DataFrame:
    """a, b and good, whether they link by whole shingle sets."""
    if pairs.isEmpty():
        return pairs.withColumn("good", F.lit(True))
    bodies = packed(docs, stored(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), "needed"))

    def run(batches):
        for b in cut_up(batches, 4000):
            x, y = b.column(2).to_pylist(), b.column(3).to_pylist()
            of, good = unpacked(x + y, rule), []
            for s, t in zip(x, y):
                s, t = of[s], of[t]
                both = len(np.intersect1d(s, t, assume_unique=True))
                good.append(both > 0 and 100 * both >= rule.percent * (len(s) + len(t) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(good, pa.bool_())], names=["a", "b", "good"])

    both = pairs.join(bodies.select(F.col("id").alias("a"), F.col("z").alias("x")), "a").join(bodies.select(F.col("id").alias("b"), F.col("z").alias("y")), "b")
    return both.select("a", "b", "x", "y").mapInArrow(tidy(run), "a long, b long, good boolean")


def near(docs: DataFrame, rule: Rule = Rule()) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of docs (doc_id, text)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text"))
    rows, frequent = profiles(docs, rule)
    held = rows.filter("id is not null and n > 0")
    first = stored(held.groupBy("sig").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("copies")), "classes")
    same = stored(held.join(first.filter("copies > 1").drop("copies"), "sig").select(F.col("id").alias("a"), F.col("first").alias("b")).filter("a <> b").distinct(), "same")
    pre = stored(prefixes(docs, first.select("first"), frequent, rule), "prefixes")
    sizes = pre.groupBy("id").agg(F.max("n").alias("n"), F.min("p").alias("p"), F.min("l").alias("l")) if _ids_repeat(pre) else pre.select("id", "n", "p", "l")
    lists = postings(pre)

    # In every list, a star round the document of the smallest id and one round that of the smallest hash.
    centre = lists.groupBy("token").agg(F.min("id").alias("a"), F.min_by("id", F.xxhash64("id")).alias("c"))
    star = lists.join(centre, "token").select("id", F.explode(F.array_distinct(F.array("a", "c"))).alias("a")).filter("id <> a")
    star = star.groupBy(F.least("a", "id").alias("a"), F.greatest("a", "id").alias("b")).agg(F.count(F.lit(1)).alias("shared"))
    spark = docs.sparkSession
    tried = settled(spark, "tried", lambda: verify(docs, stored(_likely(star, sizes, rule), "star"), rule))
    links = same.union(tried.filter("good").select("a", "b"))
    comp = stored(components(links), "components")
    left = _mixed(lists, comp)

    few = left.filter(F.col("size") <= SHORT)
    x, y = few.alias("x"), few.alias("y")
    pairs = x.join(y, (F.col("x.token") == F.col("y.token")) & (F.col("x.id") < F.col("y.id")) & (F.col("x.k") != F.col("y.k"))).groupBy(F.col("x.id").alias("a"), F.col("y.id").alias("b")).agg(F.count(F.lit(1)).alias("shared"))
    pairs = stored(_likely(pairs, sizes, rule).join(tried.select("a", "b"), ["a", "b"], "left_anti"), "pairs")
    long = left.filter(F.col("size") > SHORT)
    more = settled(spark, "more", lambda: verify(docs, pairs, rule).filter("good").select("a", "b").union(_blocks(docs, long, sizes, rule)))
    if not more.isEmpty():
        comp = stored(components(links.union(more)), "components")
    return rows.join(comp, "id", "left").select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("component", "id").alias("component_id"))


def _blocks(docs: DataFrame, hot: DataFrame, sizes: DataFrame, rule: Rule) -> DataFrame:
    """Links (a, b) that join components, of documents that share a long list (token, id, k).

    Lists with one first document are one group: near copies share many lists, and are compared once, not once a list.
    In a group, whoever is not of its largest component is compared with everybody of other components. Both are cut
    into blocks of bounded size, and two blocks meet in one task, which counts all their overlaps as products of
    matrices. No pair becomes a row: a task returns one link for components that it joins.
    """
    centre = hot.groupBy("token").agg(F.min("id").alias("c"))
    rows = stored(hot.join(centre, "token").select("c", "id", "k").distinct().join(sizes.select("id", "n"), "id"), "groups")
    by_part = rows.groupBy("c", "k").agg(F.count(F.lit(1)).alias("m"), F.sum("n").alias("n"))
    blocks = lambda m, n: F.ceil(F.greatest(m / BLOCK, n / WEIGHT)).cast("int")
    groups = by_part.groupBy("c").agg(F.max(F.struct("m", "n", "k")).alias("most"), F.sum("m").alias("m"), F.sum("n").alias("n"), F.count(F.lit(1)).alias("parts")).filter("parts > 1")
    groups = stored(groups.select("c", F.col("most.k").alias("major"), blocks(F.col("m") - F.col("most.m"), F.col("n") - F.col("most.n")).alias("others"), blocks(F.col("most.m"), F.col("most.n")).alias("own")), "blocks")
    placed = rows.join(groups, "c").withColumn("major", F.col("k") == F.col("major"))
    slot = F.pmod(F.xxhash64("id"), F.when(F.col("major"), F.col("own")).otherwise(F.col("others"))).cast("int") + F.when(F.col("major"), F.col("others")).otherwise(0)
    meets = F.sequence(F.lit(0), F.when(F.col("major"), F.col("others")).otherwise(F.col("others") + F.col("own")) - 1)
    dealt = placed.withColumn("slot", slot).select("c", "id", "k", "slot", F.explode(meets).alias("other"))
    dealt = dealt.select("c", F.least("slot", "other").alias("i"), F.greatest("slot", "other").alias("j"), "id", "k", "slot")
    if groups.isEmpty():
        return rows.limit(0).select(F.col("c").alias("a"), F.col("id").alias("b"))
    bodies = packed(docs, stored(placed.select("id").distinct(), "needed"))

    def run(t: pa.Table) -> pa.Table:
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        z, slots = t.column("z").to_pylist(), t.column("slot").to_numpy()
        of = unpacked(z, rule)
        ids, k = t.column("id").to_numpy(), t.column("k").to_numpy()
        x, y = np.flatnonzero(slots == i), np.flatnonzero(slots == j)
        a, b = joining([of[z[r]] for r in x], [of[z[r]] for r in y], k[x], k[y], rule)
        return pa.table({"a": pa.array(ids[x[a]], pa.int64()), "b": pa.array(ids[y[b]], pa.int64())})

    return dealt.join(bodies, "id").groupBy("c", "i", "j").applyInArrow(run, "a long, b long")


def overlaps(x: list[np.ndarray], y: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """Sizes of the intersections of all sets of x with all of y."""
    out = np.zeros((len(x), len(y)), np.int64)
    if not len(x) or not len(y):
        return out
    rows = [np.repeat(np.arange(len(s)), [len(v) for v in s]) for s in (x, y)]
    _, col = np.unique(np.concatenate([*x, *y]), return_inverse=True)
    cols = np.split(col, [len(rows[0])])
    shared = np.intersect1d(*(np.unique(c) for c in cols), assume_unique=True)
    sides = []
    for r, c in zip(rows, cols):
        at = np.minimum(np.searchsorted(shared, c), max(0, len(shared) - 1))
        hit = shared[at] == c if len(shared) else np.zeros(len(c), bool)
        r, c = r[hit], at[hit]
        order = np.argsort(c, kind="stable")
        sides.append((r[order], c[order]))
    for first in range(0, len(shared), width):
        part = []
        for (r, c), n in zip(sides, out.shape):
            i, j = np.searchsorted(c, (first, first + width))
            m = np.zeros((n, min(width, len(shared) - first)), np.float32)
            m[r[i:j], c[i:j] - first] = 1
            part.append(m)
        out += (part[0] @ part[1].T).astype(np.int64)
    return out


def joining(x: list[np.ndarray], y: list[np.ndarray], kx: np.ndarray, ky: np.ndarray, rule: Rule) -> tuple[np.ndarray, np.ndarray]:
    """Places (in x, in y) of links that join components, no more than it takes to join them."""
    both = overlaps(x, y)
    size = [np.array([len(v) for v in s], np.int64) for s in (x, y)]
    good = (both > 0) & (100 * both >= rule.percent * (size[0][:, None] + size[1][None, :] - both)) & (kx[:, None] != ky[None, :])
    a, b = np.nonzero(good)
    _, one = np.unique(np.stack([np.minimum(kx[a], ky[b]), np.maximum(kx[a], ky[b])]), axis=1, return_index=True) if len(a) else (None, np.zeros(0, np.int64))
    up: dict = {}

    def top(v):
        while up.setdefault(v, v) != v:
            up[v] = v = up[up[v]]
        return v

    kept = []
    for n in one.tolist():
        p, q = top(int(kx[a[n]])), top(int(ky[b[n]]))
        if p != q:
            up[p] = q
            kept.append(n)
    return a[kept], b[kept]


def _ids_repeat(pre: DataFrame) -> bool:
    return not pre.groupBy("id").count().filter("count > 1").isEmpty()


def _mixed(lists: DataFrame, comp: DataFrame) -> DataFrame:
    """token, id, k (the document's component), size of lists that hold two components."""
    held = lists.join(comp.withColumnRenamed("component", "k"), "id", "left").withColumn("k", F.coalesce("k", "id"))
    parts = held.groupBy("token", "k").agg(F.count(F.lit(1)).alias("m")).groupBy("token").agg(F.sum("m").alias("size"), F.count(F.lit(1)).alias("parts")).filter("parts > 1")
    return stored(held.join(stored(parts.select("token", "size"), "parts"), "token"), "mixed")


def _likely(pairs: DataFrame, sizes: DataFrame, rule: Rule) -> DataFrame:
    """Pairs (a, b, shared) with enough common prefix shingles for the smaller l, and for the overlap that the threshold asks."""
    a, b = (sizes.select(F.col("id").alias(c), *(F.col(x).alias(f"{x}{c}") for x in ("n", "p", "l"))) for c in "ab")
    both = pairs.join(a, "a").join(b, "b")
    most = F.col("shared") + F.greatest(F.col("na") - F.col("pa"), F.col("nb") - F.col("pb"))
    close = (F.col("na") * 100 >= F.col("nb") * rule.percent) & (F.col("nb") * 100 >= F.col("na") * rule.percent)
    return both.filter(close & (F.col("shared") >= F.least("la", "lb")) & ((100 + rule.percent) * most >= rule.percent * (F.col("na") + F.col("nb")))).select("a", "b")


def op10_adaptive_prefixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near(documents(spark, sf_dir))


def one_of_each(docs: DataFrame, rule: Rule = Rule(5, 80)) -> DataFrame:
    """One row of each group of near copies, that of the smallest doc_id (nulls last); columns unchanged.

    Rows are told apart, not ids: rows that repeat an id or have none are documents of their own. Rows without words
    are linked with nothing and stay.
    """
    docs, row = numbered(docs)

    def others() -> DataFrame:
        found = near(docs.select(F.col(row).alias("doc_id"), "text"), rule).select(F.col("doc_id").alias("r"), F.col("component_id").alias("k"))
        many = stored(found.filter("r <> k").select("k").distinct(), "groups")
        members = found.join(many, "k").join(docs.select(F.col(row).alias("r"), F.col("doc_id").alias("d")), "r")
        return members.join(members.groupBy("k").agg(F.min(F.struct(F.col("d").isNull(), "d", "r")).alias("best")), "k").filter("r <> best.r").select("r")

    return without(docs, row, settled(docs.sparkSession, "gone", others))


__all__ = ["Rule", "mix", "near", "one_of_each", "op10_adaptive_prefixes", "prefix"]
