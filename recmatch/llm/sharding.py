"""Shards of near-equal bytes by Karmarkar-Karp differencing of indivisible groups.

Documents of equal text form a group, which no shard boundary cuts. Differencing starts with one partial
partition a group - its bytes in one slot, nothing in the others - and repeatedly combines the two with
the largest spread, one in rising, the other in falling order, until one is left. It runs in two levels:
groups are dealt by hash to buckets, each differenced in a task of its own, and what is left of the
buckets, one row of sums each, is differenced in turn on the driver. Buckets hold 4096 rows, or for more
than 16 million rows the root of their number: that is how many rows of sums there are at most, too. Ties go by group key, so reruns agree.

Law `bytes`. Null texts: one group, size 1. Empty tables: no rows. Repeated rows: all kept, with slots of
their own. A group larger than a shard's share makes its shard the largest; it is not cut.
"""

from __future__ import annotations

import heapq
import math

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, stored

#: Rows a bucket are BUCKET_ROWS or the root of their number, whatever the session's settings, so that reruns agree.
SHARDS, BUCKET_ROWS = 8, 4096


def difference(weights: list[tuple[int, ...]], k: int) -> list[list[int]]:
    """Combine partial partitions of k sums each. Returns, for each, which final slot each of its slots goes to.

    A merged node keeps its two children and, per child, the order in which their slots were laid together.
    """
    if not weights:
        return []
    heap, nodes = [], []
    for i, w in enumerate(weights):
        order = sorted(range(k), key=lambda s: -w[s])
        low = w[order[-1]]
        sums = [w[s] - low for s in order]
        nodes.append((order,))
        heap.append((-sums[0], i, sums))
    heapq.heapify(heap)
    while len(heap) > 1:
        _, a, x = heapq.heappop(heap)
        _, b, y = heap[0]
        sums = [p + q for p, q in zip(x, reversed(y))]
        order = sorted(range(k), key=sums.__getitem__, reverse=True)
        low = sums[order[-1]]
        sums = [sums[s] - low for s in order]
        nodes.append((order, a, b))
        heapq.heapreplace(heap, (-sums[0], len(nodes) - 1, sums))
    out: list[list[int]] = [[]] * len(weights)
    todo = [(heap[0][1], list(range(k)))]  # node, and where each of its sorted slots ends
    while todo:
        n, to = todo.pop()
        node = nodes[n]
        ends = [0] * k
        for place, s in enumerate(node[0]):
            ends[s] = to[place]
        if len(node) == 1:
            out[n] = ends
        else:
            todo.append((node[1], ends))
            todo.append((node[2], ends[::-1]))
    return out


def _buckets(k: int):
    def run(key, table):
        table = table.sort_by([("weight", "descending"), ("key", "ascending")])
        weights = table.column("weight").to_pylist()
        slot = [e[0] for e in difference([(w,) + (0,) * (k - 1) for w in weights], k)]
        return pa.table({"key": table.column("key"), "bucket": table.column("bucket"), "bin": pa.array(slot, pa.int32()), "weight": table.column("weight")})

    return run


def shard(docs: DataFrame, k: int = SHARDS, buckets: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot for docs (doc_id, text)."""
    spark = docs.sparkSession
    body = F.coalesce("text", F.lit(""))
    rows = stored(
        docs.select(
            F.col("doc_id").cast("long").alias("doc_id"),
            (F.octet_length(body) + 1).cast("long").alias("size"),
            F.crc32(body.cast("binary")).alias("text_crc32"),
            F.when(F.col("text").isNotNull(), F.unhex(F.sha2(body.cast("binary"), 256))).otherwise(F.lit(b"")).alias("key"),
        ),
        "sizes",
    )
    n = rows.count()
    buckets = buckets or math.ceil(n / max(BUCKET_ROWS, math.sqrt(n))) or 1
    groups = rows.groupBy("key").agg(F.sum("size").alias("weight")).withColumn("bucket", F.pmod(F.xxhash64("key"), F.lit(buckets)).cast("int"))
    bins = stored(groups.groupBy("bucket").applyInArrow(_buckets(k), "key binary, bucket int, bin int, weight long"), "bins")
    sums = bins.groupBy("bucket").pivot("bin", list(range(k))).sum("weight").fillna(0).orderBy("bucket").collect()
    ends = difference([tuple(r[str(s)] for s in range(k)) for r in sums], k)
    table = [(r["bucket"], s, e[s]) for r, e in zip(sums, ends) for s in range(k)]
    to = spark.createDataFrame(table, "bucket int, bin int, shard int")
    chunk = F.pmod(F.xxhash64("doc_id", "key"), F.lit(buckets)).cast("int")
    placed = rows.join(bins.drop("weight"), "key").join(F.broadcast(to), ["bucket", "bin"]).select("doc_id", "size", "text_crc32", "key", "shard", chunk.alias("chunk"))
    placed = stored(placed, "placed")
    counts = placed.groupBy("shard", "chunk").count()
    before = Window.partitionBy("shard").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("shard", "chunk", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"))
    # At most k rows a chunk, whatever the data.
    within = Window.partitionBy("shard", "chunk").orderBy("doc_id", "key")
    return placed.withColumn("n", F.row_number().over(within)).join(F.broadcast(offsets), ["shard", "chunk"]).select("doc_id", "size", "text_crc32", "shard", (F.col("before") + F.col("n") - 1).alias("slot"))


def op7_karmarkar_karp(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = shard(documents(spark, sf_dir))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
