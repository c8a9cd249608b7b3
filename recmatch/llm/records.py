"""Length-delimited binary records of token ids, with an offset index for shuffled reads.

A record is: payload length (u64), masked checksum of those 8 bytes (u32), payload, masked checksum of
the payload (u32), all little-endian. The mask rotates a CRC-32 right by 15 bits and adds a constant,
so that checksums of data that itself holds checksums stay independent. The payload is: doc_id (i64,
least value for null), number of ids (u32), bytes an id (u8: 2 where the vocabulary allows it, else 4),
the ids. One file for each range of doc_ids, ids ascending within and over the files; the index is a
Parquet table (doc_id, file, part, place, offset, length, n_tokens), so any record is one ranged read.

Null or empty texts: the end id alone. Repeated doc_ids: one record each, the texts in order. A lost
task leaves a file that no index row names; reads follow the index only.
"""

from __future__ import annotations

import json
import os
import struct
import uuid
import zlib
from array import array
from operator import attrgetter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_up, documents, dropped, kept_in_worker, open_fs, scratch

INDEX = "doc_id long, file string, part int, place long, offset long, length long, n_tokens long"
#: Fixed value: what the mask adds.
MASK = 0xA282EAD8
HEAD, HEAD_BYTES = "<qIB", 13
NULL_ID = -(2**63)
#: Words are kept for reuse up to this length, pieces of words up to that; so many words at most and those of the fill before; texts encoded together.
CACHED_CHARS, SHORT_CHARS, CACHED_WORDS, CHUNK = 40, 3, 100_000, 500


def masked(data: bytes) -> int:
    c = zlib.crc32(data)
    return (((c >> 15) | (c << 17)) + MASK) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    n = struct.pack("<Q", len(payload))
    return b"".join((n, struct.pack("<I", masked(n)), payload, struct.pack("<I", masked(payload))))


def unframe(data: bytes) -> bytes:
    """The payload of one record; ValueError if a length or checksum is wrong."""
    if len(data) < 16 or masked(data[:8]) != struct.unpack_from("<I", data, 8)[0]:
        raise ValueError("a record's length is damaged")
    (n,) = struct.unpack_from("<Q", data)
    payload = data[12 : 12 + n]
    if len(data) != n + 16 or masked(payload) != struct.unpack_from("<I", data, 12 + n)[0]:
        raise ValueError("a record's payload is damaged")
    return payload


def pack(doc_id: int | None, ids: np.ndarray, width: int) -> bytes:
    return struct.pack(HEAD, NULL_ID if doc_id is None else doc_id, len(ids), width) + ids.astype(f"<u{width}").tobytes()


def unpack(payload: bytes) -> tuple[int | None, np.ndarray]:
    doc_id, n, width = struct.unpack_from(HEAD, payload)
    return None if doc_id == NULL_ID else doc_id, np.frombuffer(payload, f"<u{width}", n, HEAD_BYTES)


#: Fixed value: the pattern of pieces of vocabularies that mark the ends of words.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
TOKEN_ID = attrgetter("id")
#: Fixed value: the byte-level form shows bytes that are no printable Latin-1 characters as characters from 256 on, in order.
BYTE_LEVEL = {b: 256 + i for i, b in enumerate([*range(33), *range(127, 161), 173])}


def _by_pieces(spec: dict) -> bool:
    """Whether a vocabulary lower-cases, splits by PIECES and marks the ends of words: only then may pieces be encoded alone."""
    steps = (spec.get("normalizer") or {}).get("normalizers") or []
    splits = [s for s in (spec.get("pre_tokenizer") or {}).get("pretokenizers") or [] if s["type"] == "Split"]
    return [s["type"] for s in steps] == ["NFC", "Replace", "Lowercase"] and [s["pattern"] for s in splits] == [{"Regex": PIECES}] and spec["model"].get("end_of_word_suffix") == "</w>"


class Encoder:
    """A tokenizers file, encoding word by word with a cache.

    The vocabulary marks the ends of words, and neither its normalizer nor its merges look past a
    piece (a run of letters, one digit, a run of other signs), so equal pieces get equal ids. No piece
    holds a blank, so a word between blanks is cut into the same pieces alone. Texts with characters
    outside the Latin blocks, or with the strings of special tokens, go to the library whole.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import regex
        from tokenizers import Tokenizer

        self.tool = Tokenizer.from_file(path)
        vocab = self.tool.get_vocab()
        self.width = 2 if max(vocab.values()) < 2**16 else 4
        self.special = [k for k, v in self.tool.get_added_tokens_decoder().items()] and [t.content for t in self.tool.get_added_tokens_decoder().values()]
        spec = json.loads(self.tool.to_str())
        self.piecewise = _by_pieces(spec)
        steps = (spec.get("pre_tokenizer") or {}).get("pretokenizers") or []
        self.model, self.direct = self.tool.model, [x["type"] for x in steps] == ["Split", "ByteLevel"] and not steps[1].get("add_prefix_space")
        self.plain = regex.compile(r"[\t-\r -~\xa1-ɏ]*+")
        self.pieces = regex.compile(PIECES).findall
        self.cache: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.short: dict[str, bytes] = {}

    def whole(self, text: str) -> bytes:
        return array("I", self.tool.encode(text, add_special_tokens=False).ids).tobytes()

    def piece(self, text: str) -> bytes:
        """Ids of one lower-case piece of the Latin blocks: the model takes its byte-level form. Printable ASCII is its own."""
        if not self.direct:
            return self.whole(text)
        if not text.isascii():
            text = text.encode().decode("latin-1").translate(BYTE_LEVEL)
        return array("I", map(TOKEN_ID, self.model.tokenize(text))).tobytes()

    def learn(self, unknown: list[str]) -> None:
        """Enter words into the cache. When it is full, the words of the last fill stay at hand until the next."""
        if len(self.cache) > CACHED_WORDS:
            self.older, self.cache = self.cache, {}
        cache, older, pieces, piece, short = self.cache, self.older, self.pieces, self.piece, self.short

        def part(text: str) -> bytes:
            ids = short.get(text)
            if ids is None:
                ids = cache.get(text) or older.get(text) or piece(text)
                if len(text) <= SHORT_CHARS:
                    short[text] = ids
            return ids

        if len(short) > CACHED_WORDS:
            short.clear()
        for w in unknown:
            ids = older.get(w)
            if ids is None:
                ids = piece(w) if w.isalpha() else b"".join(map(part, pieces(w)))
            cache[w] = ids

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian u32. Python sees each different word once, Arrow and numpy see them all."""
        plain = [self.piecewise and self.plain.fullmatch(t) is not None and not any(s in t for s in self.special) for t in texts]
        lists = pc.ascii_split_whitespace(pa.array([t.lower() if p else "" for t, p in zip(texts, plain)], pa.large_string()))
        each = lists.values.dictionary_encode()
        held = pc.binary_join(pa.ListArray.from_arrays([0, len(each.dictionary)], each.dictionary), pa.scalar(" ", pa.large_string()))[0].as_py().split(" ") if len(each) else []
        at = each.indices.to_numpy()
        full = len(self.cache) > CACHED_WORDS
        unknown = held if full else [w for w in held if w not in self.cache]
        self.learn(unknown)
        codes = [self.cache[w] for w in held]
        for w in unknown:
            if len(w) > CACHED_CHARS:
                del self.cache[w]
        size = np.fromiter(map(len, codes), np.int64, len(codes)) // 4
        n, begin = size[at], np.cumsum(size) - size
        end = np.concatenate([[0], np.cumsum(n)])
        place = np.repeat(begin[at] - end[:-1], n)
        place += np.arange(end[-1])
        ids = np.frombuffer(b"".join(codes), "<u4")[place]
        ends = end[lists.offsets.to_numpy()].tolist()
        return [ids[i:j].tobytes() if p else self.whole(t) for t, p, i, j in zip(texts, plain, ends, ends[1:])]


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def write_records(docs: DataFrame, where: str, path: str | None = None, end_id: int = 1) -> DataFrame:
    """Encode docs (doc_id, text) into record files below `where`; returns the index."""
    path = path or vocabulary()
    fs, root = open_fs(where)
    fs.create_dir(f"{root}/data")

    def run(batches):
        part = TaskContext.get().partitionId()
        name = f"part-{part:06d}-{uuid.uuid4().hex[:8]}.rec"
        fs, root = open_fs(where)
        tool = kept_in_worker(f"records {path}", lambda: Encoder(path))
        tail, offset, place, out = struct.pack("<I", end_id), 0, 0, None
        try:
            for b in cut_up(batches):
                ids, texts, rows = b.column(0).to_pylist(), b.column(1).to_pylist(), []
                for i in range(0, len(ids), CHUNK):
                    for doc_id, code in zip(ids[i : i + CHUNK], tool.encode([t or "" for t in texts[i : i + CHUNK]])):
                        record = frame(pack(doc_id, np.frombuffer(code + tail, "<u4"), tool.width))
                        out = out or fs.open_output_stream(f"{root}/data/{name}")
                        out.write(record)
                        rows.append((doc_id, place, offset, len(record), len(code) // 4 + 1))
                        offset += len(record)
                        place += 1
                if rows:
                    doc_id, at, off, n, k = zip(*rows)
                    yield pa.RecordBatch.from_arrays([pa.array(doc_id, pa.int64()), pa.array([name] * len(rows)), pa.array([part] * len(rows), pa.int32()), pa.array(at, pa.int64()), pa.array(off, pa.int64()), pa.array(n, pa.int64()), pa.array(k, pa.int64())], names=["doc_id", "file", "part", "place", "offset", "length", "n_tokens"])
        finally:
            if out:
                out.close()

    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    docs.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(run, INDEX).write.parquet(f"{where}/index")
    return docs.sparkSession.read.schema(INDEX).parquet(f"{where}/index")


def read_records(index: DataFrame, where: str) -> DataFrame:
    """Index rows with their records' ids (little-endian u32), verified; index rows may come in any order."""

    def run(batches):
        fs, root = open_fs(where)
        name, source = None, None
        for b in batches:
            ids, crc, data = [], [], []
            for f, off, n in zip(*(b.column(c).to_pylist() for c in ("file", "offset", "length"))):
                if f != name:
                    name, source = f, fs.open_input_file(f"{root}/data/{f}")
                source.seek(off)
                doc_id, got = unpack(unframe(source.read(n)))
                ids.append(doc_id)
                data.append(got.astype("<u4").tobytes())
                crc.append(zlib.crc32(data[-1]))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), b.column("part"), b.column("place"), pa.array([len(x) // 4 for x in data], pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "part", "place", "n_tokens", "ids_crc32"])

    return index.mapInArrow(run, "doc_id long, part int, place long, n_tokens long, ids_crc32 long")


def starts(index: DataFrame) -> DataFrame:
    """Per file: ids in all files before it. One row a file, so the table is as small as the list of files."""
    sums = index.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    rows = sorted((r["part"], r["n"]) for r in sums.collect())
    at, out = 0, []
    for part, n in rows:
        out.append((part, at))
        at += n
    return index.sparkSession.createDataFrame(out, "part int, part_start long")


def digest(docs: DataFrame, where: str, path: str | None = None, end_id: int = 1) -> DataFrame:
    """Write the records, read them back, and return start, length and checksum of each document's ids."""
    from pyspark.sql import Window

    index = write_records(docs, where, path, end_id)
    before = Window.partitionBy("part").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    read = read_records(index, where)
    return (
        read.withColumn("in_part", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))
        .join(F.broadcast(starts(index)), "part")
        .select("doc_id", (F.col("part_start") + F.col("in_part")).alias("start"), "n_tokens", "ids_crc32")
    )


def op2_binary_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(documents(spark, sf_dir), scratch(spark, "records"))


__all__ = ["Encoder", "digest", "dropped", "frame", "op2_binary_records", "pack", "read_records", "starts", "unframe", "unpack", "write_records"]
