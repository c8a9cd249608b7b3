"""All pairs of records whose sets of grams overlap enough, exactly, without a row for each gram that two records share.

Grams stand in one order of the whole collection, rare before frequent. Two sets that overlap enough share a gram of their prefixes;
the place of the first bounds what they can share. Prefixes meet by ranges of hashes, packed, and leave as pairs, which are verified on
whole sets. Equal sets are one class and meet once. Grams and sets are 64-bit hashes: a collision would count as equal.
"""

from __future__ import annotations

import gc
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

Store = Callable[[DataFrame, str], DataFrame]
#: Grams counted together when looking for frequent ones; how many of these are ordered by count; postings a range, bytes of grams and pairs a slot.
CHUNK, FREQUENT, RANGE, WEIGHT, PAIRS = 1 << 21, 1 << 18, 1 << 21, 1 << 25, 1 << 19
#: Records unpacked at once, and bits of a filter of classes.
ROWS, BITS = 128, 26
LONG = 5
#: Odd numbers without a pattern, for hashes.
ODD = (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)


@contextmanager
def passing(spark: SparkSession, where: str) -> Iterator[Store]:
    """store(df, name) writes a table below a shared folder; all are deleted at the end. Shuffles that nobody can read go after each."""
    made: list[str] = []

    def rest():
        gc.collect()
        spark.sparkContext._jvm.System.gc()

    def store(df: DataFrame, name: str) -> DataFrame:
        path = f"{where.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"
        made.append(path)
        df.write.parquet(path)
        rest()
        return spark.read.schema(df.schema).parquet(path)

    try:
        yield store
    finally:
        for path in made:
            p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        rest()


def mixed(h):
    import numpy as np

    h = (h ^ (h >> np.uint64(30))) * np.uint64(ODD[1])
    h = (h ^ (h >> np.uint64(27))) * np.uint64(ODD[2])
    return h ^ (h >> np.uint64(31))


def grams(lists):
    """(hashes, ends): the grams of LONG words of each list of word hashes, one after another. Shorter lists and nulls are one gram."""
    import numpy as np

    size = np.nan_to_num(lists.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
    v = lists.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
    first = np.cumsum(size) - size
    number = np.maximum(size - LONG + 1, 1)
    row = np.repeat(np.arange(len(size)), number)
    ends = np.cumsum(number)
    at = np.arange(len(row)) - np.repeat(ends - number, number) + first[row]
    h = np.minimum(size, LONG)[row].astype(np.uint64)
    for i in range(LONG):
        there = i < size[row]
        h = h * np.uint64(ODD[0]) + np.where(there, v[np.minimum(at + i, max(0, len(v) - 1))] if len(v) else np.uint64(0), np.uint64(0))
    return mixed(h), ends


def records(batches):
    """(batch, row, distinct grams in order, hash of the set) of each record; the last column holds its words."""
    import hashlib

    import numpy as np

    for whole in batches:
        for lo in range(0, whole.num_rows, ROWS):
            b = whole.slice(lo, ROWS)
            g, ends = grams(b.column(b.num_columns - 1))
            for i, (x, y) in enumerate(zip([0, *ends[:-1]], ends)):
                own = np.sort(g[x:y])
                own = own[np.concatenate([[True], own[1:] != own[:-1]])]
                yield b, i, own, int.from_bytes(hashlib.blake2b(own.tobytes(), digest_size=8).digest(), "little", signed=True)


def profiles(docs: DataFrame) -> DataFrame:
    """rid, a, b, cls, n of every record, and (h, c): grams that a chunk of sets holds four times and more."""
    import numpy as np
    import pyarrow as pa

    names = ["rid", "a", "b", "cls", "n", "h", "c"]

    def run(batches):
        rows, have, size, seen = [], [], 0, set()

        def out():
            h, c = np.unique(np.concatenate(have), return_counts=True) if have else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
            h, c = h[c > 3].view(np.int64), c[c > 3]
            cols = list(zip(*rows)) if rows else [[]] * 5
            types = [pa.int64(), pa.bool_(), pa.bool_(), pa.int64(), pa.int64()]
            few = [pa.concat_arrays([pa.array(x, t), pa.nulls(len(h), t)]) for x, t in zip(cols, types)]
            return pa.RecordBatch.from_arrays([*few, *(pa.concat_arrays([pa.nulls(len(rows), pa.int64()), pa.array(x)]) for x in (h, c))], names=names)

        for b, i, own, cls in records(batches):
            rows.append((*(b.column(k)[i].as_py() for k in range(3)), cls, len(own)))
            if cls not in seen:
                seen.add(cls)
                have.append(own)
                size += len(own)
            if size >= CHUNK:
                yield out()
                rows, have, size, seen = [], [], 0, set()
        yield out()

    return docs.select("rid", "a", "b", "w").mapInArrow(run, "rid long, a boolean, b boolean, cls long, n long, h long, c long")


def least(percent: int, n):
    """Shared grams that sets of together n grams need for percent of their union."""
    return -(-percent * n // (100 + percent))


def postings(docs: DataFrame, frequent, percent: int, ranges: int) -> DataFrame:
    """p, z: prefixes by range of hashes, as packed tables of sets (class, grams, sides, postings) and of their postings (hash, place)."""
    import numpy as np
    import pyarrow as pa

    at = np.argsort(frequent["h"].to_numpy().view(np.uint64))
    sent = docs.sparkSession.sparkContext.broadcast((frequent["h"].to_numpy()[at].tobytes(), frequent["c"].to_numpy()[at].astype(np.int64).tobytes()))

    def run(batches):
        import zstandard

        pack = zstandard.ZstdCompressor(level=1)
        known, count = (np.frombuffer(x, t) for x, t in zip(sent.value, (np.uint64, np.int64)))
        seen, mine, tokens, places, size = set(), [], [], [], 0

        def out():
            t, place = np.concatenate(tokens), np.concatenate(places)
            cls, n, side = (np.array(x, d) for x, d in zip(zip(*mine), (np.int64, np.int32, np.int8)))
            who = np.repeat(np.arange(len(mine)), [len(x) for x in tokens])
            part = ((t >> np.uint64(32)) * np.uint64(ranges) >> np.uint64(32)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            t, place, who, part = (t & np.uint64(2**32 - 1)).astype(np.uint32)[order], place[order], who[order], part[order]
            ends = np.searchsorted(part, np.arange(ranges + 1))
            found, z = [], []
            for p, (x, y) in enumerate(zip(ends, ends[1:])):
                if x < y:
                    of, k = np.unique(who[x:y], return_counts=True)
                    step = np.diff(place[x:y], prepend=0).astype(np.int32)
                    found.append(p)
                    z.append(pack.compress(b"".join([np.int64([len(of), y - x]).tobytes(), *(c.tobytes() for c in (cls[of], n[of], side[of], k.astype(np.int32), t[x:y], step))])))
            return pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), pa.array(z, pa.binary())], names=["p", "z"])

        for b, i, own, cls in records(batches):
            side = int(b.column(0)[i].as_py()) + 2 * int(b.column(1)[i].as_py())
            if (cls, side) in seen:
                continue
            seen.add((cls, side))
            df = np.zeros(len(own), np.int8)
            if len(known):
                k = np.minimum(np.searchsorted(known, own), len(known) - 1)
                same = known[k] == own
                df[same] = np.log2(count[k[same]]).astype(np.int8)
            keep = len(own) + (-percent * len(own) // 100) + 1
            mine.append((cls, len(own), side))
            tokens.append(own[np.argsort(df, kind="stable")[:keep]])
            places.append(np.arange(keep))
            size += keep
            if size >= RANGE:
                yield out()
                mine, tokens, places, size = [], [], [], 0
        if mine:
            yield out()

    return docs.select("a", "b", "w").mapInArrow(run, "p int, z binary")


def unpacked(z: list[bytes]):
    """Class, grams, sides of each set of packed tables, and of each posting its set's row, hash and place."""
    import numpy as np
    import zstandard

    tool, parts, rows = zstandard.ZstdDecompressor(), [], 0
    for x in z:
        x = tool.decompress(x)
        sets_, posts = np.frombuffer(x, np.int64, 2)
        at, cols = 16, []
        for size, kind in ((sets_, np.int64), (sets_, np.int32), (sets_, np.int8), (sets_, np.int32), (posts, np.uint32), (posts, np.int32)):
            cols.append(np.frombuffer(x, kind, size, at))
            at += cols[-1].nbytes
        cls, n, side, k, t, step = cols
        parts.append((cls, n, side, rows + np.repeat(np.arange(sets_), k), t, np.cumsum(step)))
        rows += sets_
    return [np.concatenate(c) for c in zip(*parts)]


def meeting(z: list[bytes], percent: int):
    """Pairs of classes that share a hash of a range so early in both that they can overlap enough."""
    import numpy as np

    cls, n, side, who, t, place = unpacked(z)
    ids, row = np.unique(cls, return_inverse=True)
    sizes, sides = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int8)
    sizes[row] = n
    np.bitwise_or.at(sides, row, side)
    who = row[who]
    order = np.lexsort((place, who, t))
    t, who, place = t[order], who[order], place[order]
    once = np.concatenate([[True], (t[1:] != t[:-1]) | (who[1:] != who[:-1])])
    again = np.concatenate([[False], t[once][1:] == t[once][:-1], [False]])
    t, who, place = (x[once][again[1:] | again[:-1]] for x in (t, who, place))
    order = np.lexsort((sizes[who], t))
    t, who, place = t[order], who[order], place[order]
    size, side = sizes[who], sides[who]
    found, held, i, step = [], 0, np.arange(len(t)), 1
    while len(i):
        i = i[i + step < len(t)]
        j = i + step
        near = (t[i] == t[j]) & (100 * size[i] >= percent * size[j])
        i, j = i[near], j[near]  # sizes rise in a list: who does not meet this one meets none of the next
        most = 1 + np.minimum(size[i] - place[i], size[j] - place[j]) - 1
        good = (most >= least(percent, size[i] + size[j])) & (((side[i] & 1) & (side[j] >> 1)) | ((side[j] & 1) & (side[i] >> 1))).astype(bool)
        x, y = who[i[good]], who[j[good]]
        found.append(np.unique(np.minimum(x, y) * len(ids) + np.maximum(x, y)))
        held += len(found[-1])
        if held > 1 << 22:
            found = [np.unique(np.concatenate(found))]
            held = len(found[0]) // 2
        step += 1
    pairs = np.unique(np.concatenate(found)) if found else np.zeros(0, np.int64)
    return ids[pairs // max(1, len(ids))], ids[pairs % max(1, len(ids))]


def bitmap(places: DataFrame) -> bytes:
    """A filter of fixed size of a column of places below 2**BITS. At most 2**(BITS - 6) rows reach the driver."""
    import numpy as np

    words = places.groupBy(F.shiftright("p", 6).cast("int").alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 64 as int))")).alias("v")).toArrow()
    out = np.zeros(2 ** (BITS - 6), np.int64)
    out[words["at"].to_numpy()] = words["v"].to_numpy()
    return out.tobytes()


def bodies(docs: DataFrame, needed: DataFrame, whole: bool) -> DataFrame:
    """cls, z: the grams of the sets that may be needed (cls), whole or the first 16 bits of each."""
    import numpy as np
    import pyarrow as pa

    low = 2**BITS - 1
    sent = docs.sparkSession.sparkContext.broadcast(bitmap(needed.select(F.col("cls").bitwiseAND(low).alias("p"))))

    def run(batches):
        bits, seen, out, held = np.frombuffer(sent.value, np.int64), set(), [], 0
        table = lambda: pa.RecordBatch.from_arrays([pa.array([c for c, _ in out], pa.int64()), pa.array([z for _, z in out], pa.binary())], names=["cls", "z"])
        for _, _, own, cls in records(batches):
            if bits[(cls & low) >> 6] >> (cls & 63) & 1 and cls not in seen:
                seen.add(cls)
                out.append((cls, (own if whole else (own >> np.uint64(48)).astype(np.uint16)).tobytes()))
                held += len(out[-1][1])
            if held > 8 << 20:
                yield table()
                out, held = [], 0
        yield table()

    return docs.select("w").mapInArrow(run, "cls long, z binary")


def overlaps(x, y, col, ends):
    """How many elements of set y stand in set x, of each pair of rows x, y, x sorted; col: small numbers, the elements of all rows one after another."""
    import numpy as np

    begins = np.concatenate([[0], ends[:-1]])
    mark, out = np.zeros(int(col.max()) + 1 if len(col) else 0, bool), np.zeros(len(x), np.int64)
    cuts = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1], [True]]))
    for lo, hi in zip(cuts, cuts[1:]):
        own = col[begins[x[lo]] : ends[x[lo]]]
        mark[own] = True
        for k in range(lo, hi):
            out[k] = np.count_nonzero(mark[col[begins[y[k]] : ends[y[k]]]])
        mark[own] = False
    return out


def verified(docs: DataFrame, pairs: DataFrame, percent: int, mean: float, whole: bool, store: Store) -> DataFrame:
    """a, b, share of the pairs of classes that overlap enough, by whole sets, or that may, by 16 bits of each gram, which never count less.

    Pairs of one neighbourhood go to one slot, which gets each of its sets once.
    """
    import numpy as np
    import pyarrow as pa

    some = pairs.count()
    if not some:
        return pairs.withColumn("share", F.lit(1.0))
    kind = np.uint64 if whole else np.uint16
    both = pairs.unionAll(pairs.select("b", "a"))
    one = both.groupBy("a").agg(F.least("a", F.min("b")).alias("f"))
    named = store(one, "named")
    needed = named.select(F.col("a").alias("cls"))
    two = store(both.join(named.withColumnRenamed("a", "b"), "b").groupBy("a").agg(F.min("f").alias("f")), "near")  # two steps lead to nearly the same in a group of near copies
    near = pairs.join(two, "a").select("a", "b", "f")
    many = near.groupBy("f").agg(F.ceil(F.count(F.lit(1)) / PAIRS).alias("k"))
    slots = int(max(docs.sparkSession.sparkContext.defaultParallelism, some // PAIRS, needed.count() * mean * kind().nbytes // WEIGHT)) + 1
    slot = F.pmod(F.xxhash64("f", F.pmod(F.xxhash64("a"), "k")), F.lit(slots)).cast("int")
    placed = store(near.join(many, "f").select("a", "b", slot.alias("slot")), "placed")
    wanted = placed.select(F.col("slot").alias("s"), F.col("a").alias("cls")).unionAll(placed.select("slot", "b")).distinct()
    dealt = bodies(docs, needed, whole).dropDuplicates(["cls"]).join(wanted, "cls")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64()), "share": pa.array([], pa.float64())})
        cls = right["cls"].to_numpy()
        by = np.argsort(cls)
        z = right["z"].to_pylist()
        z = [z[i] for i in by]
        ends = np.cumsum([len(s) // kind().nbytes for s in z])
        col = np.frombuffer(b"".join(z), kind)
        if whole:
            _, col = np.unique(col, return_inverse=True)
        a, b = left["a"].to_numpy(), left["b"].to_numpy()
        order = np.argsort(a, kind="stable")
        a, b = a[order], b[order]
        x, y = np.searchsorted(cls[by], a), np.searchsorted(cls[by], b)
        n, both = np.diff(ends, prepend=0), overlaps(x, y, col, ends)
        good = both >= least(percent, n[x] + n[y])
        return pa.table({"a": a[good], "b": b[good], "share": (both / (n[x] + n[y] - both))[good] if whole else np.ones(good.sum())})

    return placed.groupBy("slot").cogroup(dealt.groupBy("s")).applyInArrow(run, "a long, b long, share double")


def banded(docs: DataFrame, bands: int, rows: int, ranges: int) -> DataFrame:
    """p, band, cls: hashes of a set's bands of least hashes, by range."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        seeds = mixed(np.arange(1, bands * rows + 1, dtype=np.uint64) * np.uint64(ODD[0]))[:, None]
        seen, found, held = set(), [], []
        table = lambda: pa.RecordBatch.from_arrays([pa.array((band % np.uint64(ranges)).astype(np.int32)) if len(band) else pa.array([], pa.int32()), pa.array(band.view(np.int64)), pa.array(np.repeat(np.array(held, np.int64), bands))], names=["p", "band", "cls"])
        for _, _, own, cls in records(batches):
            if cls in seen:
                continue
            seen.add(cls)
            least_ = mixed(own[None, :] ^ seeds).min(1).reshape(bands, rows)
            h = np.arange(1, bands + 1, dtype=np.uint64)
            for r in range(rows):
                h = mixed(h * np.uint64(ODD[0]) + least_[:, r])
            found.append(h)
            held.append(cls)
            if len(held) >= 10000:
                band = np.concatenate(found)
                yield table()
                found, held = [], []
        band = np.concatenate(found) if found else np.zeros(0, np.uint64)
        yield table()

    return docs.select("w").mapInArrow(run, "p int, band long, cls long")


def sharing(band, cls):
    """Pairs of classes that share a band of a range, each once."""
    import numpy as np

    ids, who = np.unique(cls, return_inverse=True)
    order = np.lexsort((who, band))
    band, who = band[order], who[order]
    once = np.concatenate([[True], (band[1:] != band[:-1]) | (who[1:] != who[:-1])])
    band, who = band[once], who[once]
    found, held, i, step = [np.zeros(0, np.int64)], 0, np.arange(len(band)), 1
    while len(i):
        i = i[i + step < len(band)]
        i = i[band[i] == band[i + step]]
        found.append(np.unique(who[i] * len(ids) + who[i + step]))
        held += len(found[-1])
        if held > 1 << 22:
            found = [np.unique(np.concatenate(found))]
            held = len(found[0]) // 2
        step += 1
    pairs = np.unique(np.concatenate(found))
    return ids[pairs // max(1, len(ids))], ids[pairs % max(1, len(ids))]


def similar(docs: DataFrame, percent: int, store: Store, bands: tuple[int, int] | None = None) -> DataFrame:
    """x, y, share: ids of different records of docs (rid, a, b, w), x of side a and y of side b, whose grams overlap in percent of their union or more.

    w: hashes of a record's words in order. rid is not null, and no two records have the same. bands: (bands, rows) of MinHash values, of
    which a pair must share a band; otherwise none is missed.
    """
    import pyarrow as pa

    both = store(profiles(docs), "profiles")
    rows = both.filter("cls is not null").select("rid", "a", "b", "cls", "n")
    number, total = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    cores = docs.sparkSession.sparkContext.defaultParallelism
    table = lambda x, y: pa.table({"a": pa.array(x, pa.int64()), "b": pa.array(y, pa.int64())})
    if bands:
        ranges = int(max(cores, number * bands[0] // RANGE + 1))
        meet = lambda t: table(*sharing(t["band"].to_numpy(), t["cls"].to_numpy()))
        dealt = banded(docs, *bands, ranges)
    else:
        frequent = both.filter("h is not null").groupBy("h").agg(F.sum("c").alias("c")).orderBy(F.desc("c"), "h").limit(FREQUENT).toArrow()
        ranges = int(max(cores, total * (100 - percent) // 100 // RANGE + 1))
        meet = lambda t: table(*meeting(t["z"].to_pylist(), percent))
        dealt = postings(docs, frequent, percent, ranges)

    def run(t: pa.Table) -> pa.Table:
        return meet(t)

    met = store(dealt.groupBy("p").applyInArrow(run, "a long, b long"), "met")
    pairs = store(met.distinct(), "pairs")
    mean = total / max(1, number)
    maybe = store(verified(docs, pairs, percent, mean, False, store), "maybe").select("a", "b")
    good = store(verified(docs, maybe, percent, mean, True, store), "good")
    linked = good.unionAll(good.select("b", "a", "share"))
    same = rows.groupBy("cls").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.col("cls").alias("a"), F.col("cls").alias("b"), F.lit(1.0).alias("share"))
    x = rows.filter("a").select(F.col("cls").alias("a"), F.col("rid").alias("x"))
    y = rows.filter("b").select(F.col("cls").alias("b"), F.col("rid").alias("y"))
    return linked.unionAll(same).join(x, "a").join(y, "b").filter("x <> y").select("x", "y", "share")
