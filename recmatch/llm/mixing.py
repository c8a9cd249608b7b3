"""Mixing sources to target weights by a low-discrepancy schedule.

Sources get targets: their weights' shares of the whole, none above twice its source's size; what is
above goes to the others by weight. The schedule is a sequence of slots. Slot k is the point
frac(k * golden ratio), laid on the unit interval that the sources divide by their targets, so any
stretch of the schedule holds each source near its share. A source's slots are numbered in order, and
its slot r takes block r: the r-th run of `block` words of its documents, shuffled by hash and laid end
to end, again from the start after the last. No slot reaches beyond the source's target.

DataFrame functions only. Prefix sums run in two levels (chunks, then within a chunk), so that a source
with a third of all rows is no task of its own. Null sources are one source, the last. Null texts: size
0, taken 0. Repeated rows are documents of their own. Empty tables: no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, numbered, settled, stored

#: Weights by the sources' code-point order, repeating; what is taken at most of a source, and of all.
WEIGHTS, CEILING, WHOLE = (5.0, 2.0, 1.0), 2.0, 1.5
#: The golden ratio's fraction times 2**31, odd, so that 2**31 slots visit 2**31 points.
STEP, POINTS = 1327217885, 2**31
#: Documents a chunk are CHUNK_DOCS or the root of their number, whatever the session's settings, so that reruns agree.
CELLS, CHUNK_SLOTS, CHUNK_DOCS = 4096, 65536, 1024


def sized(docs: DataFrame, row: str | None = None) -> DataFrame:
    """row tells documents apart: a column's values, or else numbers."""
    return docs.select(
        (F.col(row) if row else F.monotonically_increasing_id()).alias("row"),
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("source").cast("string").alias("source"),
        F.coalesce(F.regexp_count(F.col("text"), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long").alias("size"),
    )


def targets(sizes: DataFrame, weights=WEIGHTS, ceiling: float = CEILING, whole: float = WHOLE) -> DataFrame:
    """source_key, source, source_size, target. One row a source.

    Sorted by ceiling per weight, the sources that stop at their ceiling come first; the level of the
    others is what is left of the whole over the weights that are left.
    """
    by = Window.orderBy(F.col("source").isNull(), "source")
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("source_key", F.row_number().over(by)).withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), ((F.col("source_key") - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("cap", ceiling * F.col("source_size"))
    up = Window.orderBy(F.col("cap") / F.col("weight"), "source_key")
    before, after = up.rowsBetween(Window.unboundedPreceding, -1), up.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (whole * F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    s = s.withColumn("level", level).withColumn("open", F.col("level") * F.col("weight") <= F.col("cap"))
    s = s.withColumn("level", F.min(F.when(F.col("open"), F.struct(F.col("cap") / F.col("weight"), "source_key", "level"))).over(everything)["level"])
    return s.select("source_key", "source", "source_size", F.least("cap", F.coalesce(F.col("level") * F.col("weight"), F.col("cap"))).alias("target"))


def block_words(t: DataFrame) -> int:
    """Words a block: a 256th of the smallest target above 0, from 16 to 1024."""
    least = t.filter("target > 0").agg(F.min("target")).first()[0]
    return int(max(16, min(1024, (least or 0) // 256)))


def schedule(t: DataFrame, block: int, chunk: int = CHUNK_SLOTS) -> DataFrame:
    """slot, source_key, block_no. A source's blocks are numbered from 0, its last ends at its target."""
    spark = t.sparkSession
    whole = t.agg(F.sum("target")).first()[0] or 0.0
    up = Window.orderBy("source_key").rowsBetween(Window.unboundedPreceding, 0)
    share = F.col("target") / F.lit(whole or 1.0)
    cuts = t.filter("target > 0").withColumn("to", F.sum(share).over(up)).withColumn("from", F.col("to") - share)
    # Slots meet sources over cells of the unit interval: an equal join, one row a source and cell it touches.
    cells = cuts.select("source_key", "target", "from", "to", F.explode(F.sequence(F.floor(F.col("from") * CELLS), F.least(F.floor(F.col("to") * CELLS), F.lit(CELLS - 1)))).alias("cell"))
    last = cuts.agg(F.max("to")).first()[0]
    slots = spark.range(int(-(-whole // block)) + 1 if whole else 0).select(F.col("id").alias("slot"), ((F.col("id") % POINTS) * STEP % POINTS / F.lit(float(POINTS)) * F.lit(last or 1.0)).alias("u"))
    slots = slots.withColumn("cell", F.floor(F.col("u") * CELLS)).join(F.broadcast(cells), "cell").filter("u >= from and u < to").select("slot", "source_key", "target")
    slots = slots.withColumn("chunk", F.floor(F.col("slot") / chunk))
    rank = Window.partitionBy("source_key", "chunk").orderBy("slot")
    before = Window.partitionBy("source_key").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    counts = slots.groupBy("source_key", "chunk").count().select("source_key", "chunk", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"))
    slots = slots.withColumn("n", F.row_number().over(rank)).join(counts, ["source_key", "chunk"])
    return slots.withColumn("block_no", F.col("before") + F.col("n") - 1).filter(F.col("block_no") * block < F.floor("target")).select("slot", "source_key", "block_no")


def laid(sizes: DataFrame, t: DataFrame, seed: int = 7, chunks: int | None = None) -> DataFrame:
    """Each document's place in its source's shuffled stream: at, the words before it."""
    rows = sizes.count()
    chunks = chunks or math.ceil(rows / max(CHUNK_DOCS, math.sqrt(rows))) or 1
    h = F.xxhash64(F.lit(seed), F.col("doc_id"))
    d = sizes.join(F.broadcast(t), sizes["source"].eqNullSafe(t["source"])).select("row", "doc_id", "source_key", "size", "source_size", "target", h.alias("h"))
    d = d.withColumn("chunk", F.pmod(F.shiftrightunsigned("h", 16), F.lit(chunks)).cast("int"))
    before = Window.partitionBy("source_key").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    sums = d.groupBy("source_key", "chunk").agg(F.sum("size").alias("n")).select("source_key", "chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("chunk_at"))
    inside = Window.partitionBy("source_key", "chunk").orderBy("h", "doc_id", "size", "row").rowsBetween(Window.unboundedPreceding, -1)
    d = d.withColumn("in_chunk", F.coalesce(F.sum("size").over(inside), F.lit(0))).join(sums, ["source_key", "chunk"])
    return d.select("row", "doc_id", "source_key", "size", "source_size", "target", (F.col("chunk_at") + F.col("in_chunk")).alias("at"))


def pieces(placed: DataFrame, block: int, passes: int = 2) -> DataFrame:
    """The parts of documents that fall into blocks, over so many passes through each source."""
    start: Column = F.col("at") + F.col("pass") * F.col("source_size")
    p = placed.filter("size > 0").withColumn("pass", F.explode(F.sequence(F.lit(0), F.lit(passes - 1)))).withColumn("from", start)
    p = p.withColumn("to", F.least(F.col("from") + F.col("size"), F.floor("target"))).filter("from < to")
    p = p.withColumn("block_no", F.explode(F.sequence(F.floor(F.col("from") / block), F.floor((F.col("to") - 1) / block))))
    n = F.least("to", (F.col("block_no") + 1) * block) - F.greatest("from", F.col("block_no") * block)
    return p.select("row", "doc_id", "at", "source_key", "pass", "block_no", n.alias("n_words"))


def mix(docs: DataFrame, weights=WEIGHTS, ceiling: float = CEILING, whole: float = WHOLE, block: int | None = None, row: str | None = None) -> tuple[DataFrame, DataFrame]:
    """(documents with what the mix takes of them, schedule with its pieces of documents)."""
    sizes = stored(sized(docs, row), "sizes")
    t = stored(targets(sizes, weights, ceiling, whole), "targets")
    block = block or block_words(t)
    placed = stored(laid(sizes, t), "laid")
    plan = schedule(t, block).join(pieces(placed, block, math.ceil(ceiling)), ["source_key", "block_no"])
    taken = plan.groupBy("row").agg(F.sum("n_words").alias("taken"))
    full = placed.filter("size > 0").join(taken, "row", "left").unionByName(placed.filter("size = 0").withColumn("taken", F.lit(0).cast("long")))
    out = full.select("row", "doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).alias("taken"), "source_key")
    return out, plan


def op9_low_discrepancy_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir))[0].drop("source_key", "row")


def take(docs: DataFrame, **how) -> DataFrame:
    """docs as the mix takes them: a row for each whole time that it takes a document, halves rounded up; columns unchanged. Rows are told apart, not ids.

    The join moves the texts whatever the number of rows: a table of a number each is broadcast on small inputs only.
    """
    names = docs.columns
    docs, row = numbered(docs)
    n, key = f"{row}n", f"{row}r"
    times = F.floor(F.col("taken") / F.col("size") + 0.5).cast("int")
    used = settled(docs.sparkSession, "taken", lambda: mix(docs, **how, row=row)[0].filter("size > 0").select(F.col("row").alias(key), times.alias(n)).filter(F.col(n) > 0))
    both = docs.join(used.hint("merge"), F.col(row) == F.col(key))
    return both.withColumn(n, F.explode(F.sequence(F.lit(1), F.col(n)))).select(*(F.col(f"`{c}`") for c in names))
