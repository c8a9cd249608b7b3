"""Exact removal of repeated byte strings by external induced suffix sorting.

A byte goes if a string of `least` bytes that covers it starts anywhere else too, in the same document or
another. Sorting every suffix of a corpus would be wasteful: most text is unique. So suffixes are sorted
where repeats can be, and nowhere else, without loss:

1. Every window of `least` bytes picks an anchor, the leftmost least of its 200-byte fingerprints. Equal
   windows pick equal anchors. Neighbouring windows with one anchor form a stretch. Stretches whose
   anchor's fingerprint occurs once in the corpus hold no repeat.
2. Equal stretches collapse to one with its number of copies; where an anchor has no other, its copies
   repeat it whole. Else the distinct ones' bytes are fetched once.
3. Equal windows have their anchor at one place, so a stretch falls into pieces by the windows' distance to
   the anchor, and a piece is known by its core, the bytes that all its windows hold: 334 of 400. Equal
   windows lie in pieces of equal cores. Pieces are dealt and ordered by core. Cores of one piece hold no
   repeat; the others are cut into shards of bounded size between cores. All windows of a piece hold its core
   whole, so the sort gets a mark and the core's number in the shard in its place: 70 symbols a window instead of
   400 bytes, and equal windows stay equal, different ones different. Each shard's suffixes are sorted with
   their common prefixes by external induced sorting (induced.py). A common prefix of a window's length
   with a neighbour, or a copy of the piece, marks a window.
   Anchors with more than MANY different stretches would fill a task: their pieces are single windows, all
   core, for which equal cores say everything; they are counted by core, without bytes.
4. Marks go back to all stretches, and the documents are rewritten.

Texts, stretches and cores are told apart by fingerprints of 64 bits. Null texts are empty, and nothing is
removed from texts shorter than `least`. Documents may share ids or have none; rows with equal id and text
are documents of their own, each other's repeats. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, open_fs, scratch, stored
from .induced import Spill, repeated
from .jaccard import filtered, only
from .shingles import BASE, INVERSE, MIX1, mix, slices

LEAST, GRAM, SHARD = 400, 200, 2 << 20
#: Different stretches of an anchor beyond which its pieces are single windows; bytes of a sort's queues in memory.
MANY, BUDGET = 1 << 14, 4 << 20
#: Bytes of a core's number in its shard.
NUMBER = 3


def _table() -> np.ndarray:
    return mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(BASE))


class Stretches:
    """Windows' anchors and stretches of the documents of a slice."""

    def __init__(self, least: int = LEAST, gram: int = GRAM):
        self.least, self.gram, self.values = least, min(gram, max(1, least // 2)), _table()
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if n >= len(self.up):
            n = max(n + 1, 1 << 20)
            self.up, self.down = np.full(n, BASE, np.uint64), np.full(n, INVERSE, np.uint64)
            self.up[0] = self.down[0] = 1
            self.up, self.down = np.cumprod(self.up), np.cumprod(self.down)

    def own(self, data: bytes) -> int:
        """A document's hash alone, as `of` gives it, signed."""
        raw = np.frombuffer(data, np.uint8)
        self._powers(len(raw) + 1)
        whole = (self.values[raw] * self.up[: len(raw)]).sum(dtype=np.uint64)
        return int(mix(np.array([whole + np.uint64(len(raw))], np.uint64)).view(np.int64)[0])

    def of(self, data: np.ndarray, off: np.ndarray):
        """Each document's hash, and (document, anchor hash, stretch hash, first byte, end, anchor's first byte) of its stretches."""
        n, k, w = len(data), self.gram, self.least - self.gram + 1
        self._powers(n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum(self.values[data] * self.up[:n], out=total[1:])
        own = mix((total[off[1:]] - total[off[:-1]]) * self.down[off[:-1]] + np.diff(off).astype(np.uint64))
        windows = np.maximum(np.diff(off) - self.least + 1, 0)
        if not windows.any():
            return own, None
        grams = mix((total[k:] - total[:-k]) * self.down[: n - k + 1])
        bits = np.uint64(int(n).bit_length())
        packed = (grams >> bits << bits) | np.arange(len(grams), dtype=np.uint64)
        m = -(-len(packed) // w) * w + w
        padded = np.full(m, 2**64 - 1, np.uint64)
        padded[: len(packed)] = packed
        rows = padded.reshape(-1, w)
        front = np.minimum.accumulate(rows, axis=1).ravel()
        rear = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
        doc = np.repeat(np.arange(len(windows)), windows)
        start = np.arange(len(doc)) - np.repeat(np.cumsum(windows) - windows, windows) + off[:-1][doc]
        anchor = (np.minimum(rear[start], front[start + w - 1]) & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
        new = np.ones(len(doc), bool)
        new[1:] = (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1])
        head = np.flatnonzero(new)
        tail = np.append(head[1:], len(doc)) - 1
        a, b = start[head], start[tail] + self.least
        th = mix((total[b] - total[a]) * self.down[a] + (b - a).astype(np.uint64))
        d = doc[head]
        return own, (d, grams[anchor[head]], th, a - off[d], b - off[d], anchor[head] - off[d])


def merged(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs covered by intervals [a, b)."""
    order = np.argsort(a, kind="stable")
    a, b = a[order], np.maximum.accumulate(b[order])
    new = np.ones(len(a), bool)
    new[1:] = a[1:] > b[:-1]
    return a[new], np.append(b[:-1][new[1:]], b[-1:]) if len(a) else b


def stretches(docs: DataFrame, least: int) -> DataFrame:
    """id, x (hash of the text), h, t, a, b, p: arrays, one row a document that has windows."""
    names, kinds = ("h", "t", "a", "b", "p"), (np.int64, np.int64, np.int32, np.int32, np.int32)

    def run(batches):
        tool = Stretches(least)
        for c in batches:
            ids, xs, cols, sizes = [], [], [[] for _ in names], []
            for data, off, row in slices(c.column(1)):
                own, got = tool.of(data, off)
                if got is None:
                    continue
                d, *rest = got
                which, n = np.unique(d, return_counts=True)
                ids += [c.column(0)[int(row + i)].as_py() for i in which]
                xs.append(own[which])
                sizes.append(n)
                for x, y, kind in zip(cols, rest, kinds):
                    x.append(y.view(np.int64).astype(kind, copy=False))
            ends = pa.array(np.concatenate([[0], np.cumsum(np.concatenate(sizes))]).astype(np.int32) if sizes else [0], pa.int32())
            lists = [pa.ListArray.from_arrays(ends, pa.array(np.concatenate(x) if x else np.zeros(0, kind))) for x, kind in zip(cols, kinds)]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.concatenate(xs).view(np.int64) if xs else [], pa.int64()), *lists], names=["id", "x", *names])

    return docs.mapInArrow(run, "id long, x long, h array<long>, t array<long>, a array<int>, b array<int>, p array<int>")


def hashed(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """id, x, text of the documents whose id may be among ids."""

    def run(batches):
        tool = Stretches()
        for b in batches:
            x = [tool.own(t.encode("utf-8", "surrogatepass") if t else b"") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x, pa.int64()), b.column(1)], names=["id", "x", "text"])

    return only(docs, ids, run, "id long, x long, text string")


def joined(texts: DataFrame, more: DataFrame) -> DataFrame:
    """texts (id, x, ...) with more (id, x, ...); null ids are equal."""
    more = more.withColumnsRenamed({"id": "_id", "x": "_x"})
    return texts.join(more, F.col("id").eqNullSafe(F.col("_id")) & (F.col("x") == F.col("_x"))).drop("_id", "_x")


def pieces(texts: DataFrame, least: int, piece: int) -> DataFrame:
    """h, t, n, c (hash of anchor, place and core), at (the piece's first byte in its stretch), core (the core's first byte in the piece), body of the pieces of texts (text, parts)."""

    def run(batches):
        values = _table()
        up = np.full(least + 1, BASE, np.uint64)
        up[0] = 1
        up = np.cumprod(up)
        for c in batches:
            out = []
            for text, parts in zip(c.column("text").to_pylist(), c.column("parts").to_pylist()):
                data = (text or "").encode("utf-8", "surrogatepass")
                for p in parts:
                    # Distances of windows to their anchor, from `first` down to `last`; a piece's lie in one class.
                    first, last = p["p"] - p["a"], p["p"] - p["b"] + least
                    for k in range(last // piece, first // piece + 1):
                        high, low = min(first, (k + 1) * piece - 1), max(last, k * piece)
                        core = np.frombuffer(data, np.uint8)[p["p"] - k * piece : p["p"] - (k + 1) * piece + 1 + least]
                        h = (values[core] * up[: len(core)]).sum(dtype=np.uint64) + np.uint64(k) * np.uint64(MIX1) + np.uint64(p["h"] % 2**64)
                        out.append((p["h"], p["t"], p["n"], h, p["p"] - high - p["a"], high - k * piece, data[p["p"] - high : p["p"] - low + least] if piece > 1 else None))
            cols = list(zip(*out)) or [()] * 7
            c = mix(np.array(cols[3], np.uint64)).view(np.int64)
            yield pa.RecordBatch.from_arrays([*(pa.array(v, pa.int64()) for v in cols[:3]), pa.array(c), pa.array(cols[4], pa.int32()), pa.array(cols[5], pa.int32()), pa.array(cols[6], pa.binary())], names=["h", "t", "n", "c", "at", "core", "body"])

    return texts.select("text", "parts").mapInArrow(run, "h long, t long, n long, c long, at int, core int, body binary")


def shortened(bodies: list[bytes], cores: list[int], length: int) -> list[bytes]:
    """Bodies with the `length` bytes from cores on replaced by a byte to mark and the number of those bytes."""
    known: dict[bytes, bytes] = {}
    number = [known.setdefault(b[p : p + length], len(known).to_bytes(NUMBER, "big")) for b, p in zip(bodies, cores)]
    return [b[:p] + b"\0" + n + b[p + length :] for b, p, n in zip(bodies, cores, number)]


def marked(parts: DataFrame, least: int, piece: int, where: str, shard: int = SHARD, budget: int = BUDGET) -> DataFrame:
    """h, t, spans (flat starts and ends within the stretch) of repeated windows of pieces, which come ordered by c."""
    length = least + 1 - piece  # of a core

    def run(batches):
        fs, root = open_fs(where)
        held, size = [], 0

        def found(rows, flags):
            out = []
            for (h, t, _, _, at, _, _), f in zip(rows, flags):
                if (at_ := np.flatnonzero(f)).size:
                    a, b = merged(at_, at_ + least)
                    out.append((h, t, (np.stack([a, b], 1).ravel() + at).tolist()))
            c = list(zip(*out)) or [()] * 3
            return pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.list_(pa.int32()))], names=["h", "t", "spans"])

        def sort():
            """Pieces of equal bytes and core are one string."""
            copies: dict[tuple[bytes, int], int] = {}
            for r in held:
                copies[r[6], r[5]] = copies.get((r[6], r[5]), 0) + r[2]
            bodies, cores = zip(*copies)
            flags = dict(zip(copies, repeated(shortened(bodies, cores, length), piece + NUMBER, Spill(fs, f"{root}/runs", budget), [n > 1 for n in copies.values()], list(cores))))
            return found(held, [flags[r[6], r[5]] for r in held])

        group: list = []

        def close():
            """What a core's pieces hold, at once or in the next shard."""
            nonlocal size
            if len({r[6] for r in group}) > 1:
                held.extend(group)
                size += sum(len(r[6]) - length + 1 + NUMBER for r in group)
            elif sum(r[2] for r in group) > 1:
                return found(group, [np.arange(len(r[6])) <= len(r[6]) - least for r in group])

        for b in batches:
            for r in zip(*(c.to_pylist() for c in b.columns)):
                if group and r[3] != group[0][3]:
                    if (out := close()) is not None:
                        yield out
                    group = []
                    if size >= shard:
                        yield sort()
                        held, size = [], 0
                group.append(r)
        if group and (out := close()) is not None:
            yield out
        if held:
            yield sort()

    return parts.select("h", "t", "n", "c", "at", "core", "body").mapInArrow(run, "h long, t long, spans array<int>")


def counted(parts: DataFrame, least: int) -> DataFrame:
    """h, t, spans of repeated windows of pieces that are single windows."""
    cores = parts.groupBy("c").agg(F.sum("n").alias("all")).filter("all > 1").select("c")
    return parts.join(stored(cores, "cores"), "c", "left_semi").select("h", "t", F.array(F.col("at"), (F.col("at") + least).cast("int")).alias("spans"))


def cut(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """OUT rows of all docs, with the covered bytes taken out. Only documents with spans are joined."""
    schema = "id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    names = [c.split()[0] for c in schema.split(", ")]

    def rewrite(batches):
        for c in batches:
            rows = []
            lists = c.column("spans").to_pylist() if "spans" in c.schema.names else [None] * len(c)
            for i, text, own in zip(c.column("id").to_pylist(), c.column("text").to_pylist(), lists):
                data = (text or "").encode("utf-8", "surrogatepass")
                a, b = merged(*np.array(own, np.int64).reshape(-1, 2).T) if own else (np.zeros(0, np.int64),) * 2
                sha, at = hashlib.sha256(), 0
                for p, q in zip(a.tolist(), b.tolist()):
                    sha.update(data[at:p])
                    at = q
                sha.update(data[at:])
                rows.append((i, len(data), int((b - a).sum()), len(a), sha.hexdigest()))
            cols = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in cols[:4]), pa.array(cols[4], pa.string())], names=names)

    known = stored(spans, "spans")
    if known.isEmpty():
        return docs.mapInArrow(rewrite, schema)
    texts, ids = hashed(docs, known.select("id")), known.withColumnsRenamed({"id": "_id", "x": "_x"})
    hit = texts.join(ids, F.col("id").eqNullSafe(F.col("_id")) & (F.col("x") == F.col("_x")), "left").mapInArrow(rewrite, schema)
    return only(docs, known.select("id"), rewrite, schema, inside=False).unionByName(hit)


def remove_repeats(docs: DataFrame, least: int = LEAST, shard: int = SHARD, budget: int = BUDGET, many: int = MANY) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of docs (doc_id, text)."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text"))
    runs = stored(stretches(docs, least), "stretches")

    # Anchors that occur again; the filter is of fixed size, what it lets through by chance has n = 1 below.
    again = stored(runs.select(F.explode("h").alias("h")).groupBy("h").count().filter("count > 1").select("h"), "anchors")
    rows = runs.select("id", "x", F.explode(F.arrays_zip("h", "t", "a", "b", "p")).alias("s")).select("id", "x", "s.*")
    rows = stored(filtered(rows.withColumnsRenamed({"id": "doc", "h": "id"}), again.withColumnRenamed("h", "id")).withColumnsRenamed({"id": "h", "doc": "id"}), "again")
    one = rows.groupBy("h", "t").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("id", "x", "a", "b", "p")).alias("r")).select("h", "t", "n", "r.*")
    one = stored(one.join(again, "h", "left_semi"), "distinct")

    # Where all stretches of an anchor are equal, there is nothing to order: each window of theirs is a repeat.
    texts_of = stored(one.groupBy("h").agg(F.count(F.lit(1)).alias("texts")), "texts")
    alone = one.join(texts_of.filter("texts = 1").select("h"), "h", "left_semi").filter("n > 1").select("h", "t", F.array(F.lit(0), (F.col("b") - F.col("a")).cast("int")).alias("spans"))
    found, piece = alone, max(1, (least - Stretches(least).gram + 1) // 3)
    for size, some in ((piece, texts_of.filter((F.col("texts") > 1) & (F.col("texts") <= many))), (1, texts_of.filter((F.col("texts") > 1) & (F.col("texts") > many)))):
        if some.isEmpty():
            continue
        wanted = stored(one.join(some.select("h"), "h", "left_semi").groupBy("id", "x").agg(F.collect_list(F.struct("h", "t", "n", "a", "b", "p")).alias("parts")), "wanted")  # a document's own stretches
        parts = pieces(joined(hashed(docs, wanted.select("id")), wanted), least, size)
        if size > 1:
            found = found.unionByName(marked(parts.repartition("c").sortWithinPartitions("c"), least, size, scratch(spark, "sort"), shard, budget))
        else:
            found = found.unionByName(counted(stored(parts.drop("body"), "single"), least))
    back = rows.join(stored(found, "marks"), ["h", "t"]).select("id", "x", F.transform("spans", lambda v: (v + F.col("a")).cast("int")).alias("spans"))
    per_text = back.groupBy("id", "x").agg(F.flatten(F.collect_list("spans")).alias("spans"))  # a document's own spans
    return cut(docs, per_text).withColumnRenamed("id", "doc_id")


def op1_induced_suffix_sorting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(documents(spark, sf_dir))
