"""Benchmark decontamination by size-partitioned MinHash containment search.

Test items are short, documents long, so their Jaccard similarity is near 0 even where a document holds a
whole item. Items are therefore partitioned by size: class c holds items of more than half to all of
2**c shingles. For each class a document is cut into blocks of 2**c shingles, and each two neighbouring
blocks are a window: an item's passage lies in one, and takes a fixed share of it, so the containment
bound becomes a Jaccard bound of about 0.19, which 64 MinHash values with bands of one row miss with a
chance of about one in a million. Items of few shingles would be too small a share of the smallest
windows: all their shingles are looked up as they are, which misses nothing. Candidates are verified exactly: the share of the item's distinct
five-word shingles that the whole document holds is at least 0.8.

Windows whose values miss a bitmap of fixed size, made from the items' values, never leave their task.

Words are runs of characters other than ASCII signs and blanks, A-Z lower-cased. Items of fewer than five
words match documents that hold their whole word sequence. Items or documents without words match
nothing. Repeated documents and items are rows of their own. Empty tables: no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, numbered, settled, stored, tidy, without
from .shingles import Words, mix, shingled, slices

WORDS, SHARE, VALUES, BITS = 5, 0.8, 64, 24
MIN_CLASS, MAX_CLASS = 3, 24
#: Items of so many distinct shingles at most are looked up by each shingle, not by MinHash.
DIRECT = 4
MATCH = "doc_id long, item_id long, n_item_shingles long, n_shared long, containment double"


def _steps() -> np.ndarray:
    return mix(np.arange(1, 2 * VALUES + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def size_class(n: int) -> int:
    return max(MIN_CLASS, min(MAX_CLASS, int(n - 1).bit_length()))


def _key(c: int, j: int, low: np.ndarray) -> np.ndarray:
    """A MinHash value with its class and number, as one 64-bit key."""
    return mix(low + np.uint64((c * 1000 + j + 1) * 0x632BE59BD9B4E019 % 2**64))


def _bits(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return (keys & np.uint64(2**BITS - 1)).astype(np.int64), ((keys >> np.uint64(40)) & np.uint64(2**BITS - 1)).astype(np.int64)


def item_table(items: DataFrame) -> DataFrame:
    """item_no, item_id, kind (class, or minus the words of a shingle that is looked up as it is), shingles (distinct, u64), keys."""

    def run(batches):
        tool, steps = Words("plain"), _steps()
        for b in batches:
            out = []
            for data, off, row in slices(b.column(2)):
                h, first = tool.of(data, off)
                s, ptr = shingled(h, first, WORDS)
                for i in range(len(off) - 1):
                    own = np.unique(s[ptr[i] : ptr[i + 1]])
                    if not len(own):
                        continue
                    n = int(first[i + 1] - first[i])
                    if n < WORDS:
                        kind = -n
                        own = shingled(h[first[i] : first[i + 1]], np.array([0, n]), n)[0]
                        keys = _key(kind + 100, 0, own)
                    elif len(own) <= DIRECT:
                        kind = -WORDS
                        keys = _key(kind + 100, 0, own)
                    else:
                        kind = size_class(len(own))
                        keys = np.array([_key(kind, j, (own * steps[2 * j] + steps[2 * j + 1]).min(keepdims=True))[0] for j in range(VALUES)])
                    at = row + i
                    out.append((b.column(0)[at].as_py(), b.column(1)[at].as_py(), kind, own.tobytes(), keys.view(np.int64).tolist()))
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.list_(pa.int64())))], names=["item_no", "item_id", "kind", "shingles", "keys"])

    items = items.select(F.monotonically_increasing_id().alias("item_no"), F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    return stored(items.mapInArrow(run, "item_no long, item_id long, kind int, shingles binary, keys array<long>"), "items")


def candidates(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Documents with a window whose value may be an item's: row_no, doc_id, shingles, keys."""
    spark = docs.sparkSession
    kinds = sorted(r[0] for r in items.select("kind").distinct().collect())
    low, high = (F.col("key").bitwiseAND(2**BITS - 1), F.shiftrightunsigned("key", 40).bitwiseAND(2**BITS - 1))
    keys = items.select(F.explode("keys").alias("key"))
    bitmap = np.zeros(2**BITS, np.uint8)  # at most 2**BITS distinct places, whatever the items
    for r in keys.select(F.explode(F.array(low, high + F.lit(2**BITS))).alias("p")).distinct().toArrow().column(0).to_pylist():
        bitmap[r % 2**BITS] |= 1 << (r // 2**BITS)
    sent = spark.sparkContext.broadcast(np.packbits(bitmap & 1).tobytes() + np.packbits(bitmap >> 1).tobytes())

    def run(batches):
        raw = np.unpackbits(np.frombuffer(sent.value, np.uint8)).view(bool)
        one, two = raw[: 2**BITS], raw[2**BITS :]
        tool, steps = Words("plain"), _steps()
        classes = [c for c in kinds if c > 0]
        for b in batches:
            out = []
            for data, off, row in slices(b.column(1)):
                h, first = tool.of(data, off)
                if not len(h):
                    continue
                s, ptr = shingled(h, first, WORDS)
                found: list[tuple[np.ndarray, np.ndarray]] = []
                for c in classes:
                    blocks, of_row = _blocks(ptr, 2**c)
                    if not len(blocks):
                        continue
                    same = of_row[1:] == of_row[:-1]
                    for j in range(VALUES):
                        low = np.minimum.reduceat(s * steps[2 * j] + steps[2 * j + 1], blocks)
                        window = low.copy()
                        window[:-1][same] = np.minimum(low[:-1], low[1:])[same]
                        k = _key(c, j, window)
                        hit = np.flatnonzero(one[_bits(k)[0]])
                        hit = hit[two[_bits(k[hit])[1]]]
                        if len(hit):
                            found.append((of_row[hit], k[hit]))
                for n in (-k for k in kinds if k < 0):
                    g, gp = shingled(h, first, n)
                    k = _key(100 - n, 0, g)
                    hit = np.flatnonzero(one[_bits(k)[0]])
                    hit = hit[two[_bits(k[hit])[1]]]
                    if len(hit):
                        found.append((np.searchsorted(gp, hit, "right") - 1, k[hit]))
                if not found:
                    continue
                rows, ks = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
                for r in np.unique(rows):
                    own = [s[ptr[r] : ptr[r + 1]]]
                    own += [shingled(h[first[r] : first[r + 1]], np.array([0, first[r + 1] - first[r]]), -k)[0] for k in kinds if k < 0]
                    out.append((b.column(0)[int(row + r)].as_py(), np.unique(np.concatenate(own)).tobytes(), np.unique(ks[rows == r]).view(np.int64).tolist()))
            cols = list(zip(*out)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.binary(), pa.list_(pa.int64())))], names=["doc_id", "shingles", "keys"])

    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    found = docs.mapInArrow(tidy(run), "doc_id long, shingles binary, keys array<long>")
    return stored(found.withColumn("row_no", F.monotonically_increasing_id()), "windows")


def _blocks(ptr: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of each row's blocks of `size` shingles, and their rows."""
    n = -(-np.diff(ptr) // size)
    rows = np.repeat(np.arange(len(n)), n)
    within = np.arange(len(rows)) - np.repeat(np.cumsum(n) - n, n)
    return ptr[rows] + within * size, rows


def contained(docs: DataFrame, items: DataFrame, share: float = SHARE) -> DataFrame:
    """MATCH rows: which documents (doc_id, text) hold which items (item_id, text)."""
    table = item_table(items)
    found = candidates(docs, table)
    pairs = found.select("row_no", F.explode("keys").alias("key")).join(table.select("item_no", F.explode("keys").alias("key")), "key").select("row_no", "item_no").distinct()

    def run(batches):
        for b in batches:
            n, shared = [], []
            for d, i in zip(b.column(2).to_pylist(), b.column(3).to_pylist()):
                own = np.frombuffer(i, np.uint64)
                n.append(len(own))
                shared.append(int(np.isin(own, np.frombuffer(d, np.uint64), assume_unique=True).sum()))
            part = [s / max(1, k) for s, k in zip(shared, n)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(shared, pa.int64()), pa.array(part, pa.float64())], names=[x.split()[0] for x in MATCH.split(", ")])

    both = pairs.join(found.select("row_no", "doc_id", F.col("shingles").alias("d")), "row_no").join(table.select("item_no", "item_id", F.col("shingles").alias("i")), "item_no")
    return both.select("doc_id", "item_id", "d", "i").mapInArrow(run, MATCH).filter(F.col("containment") >= share)


def clean(docs: DataFrame, items: DataFrame, share: float = SHARE) -> DataFrame:
    """The rows that hold no item, with all their columns. Rows that share an id, or have none, are judged one by one."""
    docs, row = numbered(docs)
    gone = settled(docs.sparkSession, "gone", lambda: contained(docs.select(F.col(row).alias("doc_id"), "text"), items, share).select("doc_id").distinct())
    return without(docs, row, gone)


def op6_minhash_containment(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contained(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
