"""WARC archives, and the normaliser of monolithic ones.

A writer that compresses a whole archive as one gzip stream leaves a file in which no record can be
reached without inflating all before it. The normaliser inflates such a stream once, in pieces of
bounded size, cuts it into records by their headers, rewrites every record as a gzip member of its own,
and writes beside the archive an index (offset, length, id, type, digest): any record is then one ranged
read, as the format's guidelines ask. Members, and several streams after another, are read alike.

Equal payloads: that with the smallest page_id is a response, the others revisit it. Null html: the
empty payload. A page_id that repeats is written each time, with equal payloads as a response each
time if it is the smallest. Extra columns are ignored. No rows, no archives.
"""

from __future__ import annotations

import base64
import hashlib
import json
import uuid
import zlib

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import open_fs, scratch

PIECE = 1 << 18
INDEX = "file string, offset long, length long"
RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"
#: The format's line ends and the profile of revisits.
EOL, END = b"\r\n", b"\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2000-01-01T00:00:00Z"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page_id: int | None, n: int) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page {page_id} {n}')}>"


def record(headers: list[tuple[str, str]], payload: bytes) -> bytes:
    head = ["WARC/1.1", *(f"{k}: {v}" for k, v in headers), f"Content-Length: {len(payload)}"]
    return EOL.join(x.encode() for x in head) + END + payload + END


def page_record(page_id, url, payload: bytes, refers_to, n: int, sha: str | None = None) -> bytes:
    """A response, or where refers_to is given a revisit, whose own block is empty."""
    kind = "response" if refers_to is None else "revisit"
    headers = [("WARC-Type", kind), ("WARC-Record-ID", record_id(page_id, n)), ("WARC-Date", DATE)]
    if url:
        headers.append(("WARC-Target-URI", "".join(c if " " < c < "\x7f" else "%%%02X" % (ord(c) & 255) for c in url)))
    headers += [("Content-Type", "text/html; charset=utf-8"), ("WARC-Payload-Digest", f"sha1:{sha or digest(payload)}"), ("X-Page-Id", "" if page_id is None else str(page_id)), ("X-Payload-Length", str(len(payload)))]
    if refers_to is not None:
        headers += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to, 0)), ("X-Refers-To-Page", str(refers_to))]
    return record(headers, payload if refers_to is None else b"")


def inflated(pieces):
    """Plain bytes of a gzip file of one or more streams, in pieces."""
    tool = zlib.decompressobj(31)
    for piece in pieces:
        while piece:
            if tool.eof:
                tool = zlib.decompressobj(31)
            plain = tool.decompress(piece, 4 * PIECE)
            piece = tool.unused_data if tool.eof else tool.unconsumed_tail
            if plain:
                yield plain
            elif not piece:
                break
    tail = tool.flush()
    if tail:
        yield tail
    if not tool.eof:
        raise ValueError("the gzip stream ends early")


def split(plain):
    """Whole records, as bytes, of an archive's plain bytes given in pieces; memory holds one record and a piece."""
    have, need = bytearray(), None
    for piece in plain:
        have += piece
        while True:
            if need is None:
                cut = have.find(END)
                if cut < 0:
                    break
                head = parse_head(bytes(have[:cut]))
                need = cut + 4 + int(head["content-length"]) + 4
            if len(have) < need:
                break
            if have[need - 4 : need] != END:
                raise ValueError("a record has no end")
            yield bytes(have[:need])
            del have[:need]
            need = None
    if have:
        raise ValueError("the archive ends within a record")


def parse_head(data: bytes) -> dict[str, str]:
    lines = data.split(EOL)
    if not lines[0].startswith(b"WARC/"):
        raise ValueError("a record starts with no version")
    pairs = (x.decode("utf-8").partition(":") for x in lines[1:] if x)
    return {k.strip().lower(): v.strip() for k, _, v in pairs}


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = data.partition(END)
    h = parse_head(head)
    return h, rest[: int(h["content-length"])]


def member(data: bytes) -> bytes:
    tool = zlib.compressobj(1, zlib.DEFLATED, 31)
    return tool.compress(data) + tool.flush()


def normalise(source, sink, sidecar) -> list[tuple[int, int]]:
    """Rewrite an archive record by record; (offset, length) of each member. All three are open streams."""
    out, at = [], 0
    for data in split(inflated(iter(lambda: source.read(PIECE), b""))):
        packed = member(data)
        sink.write(packed)
        head = parse_head(data[: data.find(END)])
        line = {"offset": at, "length": len(packed), "id": head.get("warc-record-id"), "type": head.get("warc-type"), "digest": head.get("warc-payload-digest")}
        sidecar.write(json.dumps(line).encode() + b"\n")
        out.append((at, len(packed)))
        at += len(packed)
    return out


def digested(pages: DataFrame) -> DataFrame:
    """page_id, url, html, with payload's digest and the page it revisits."""
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("html"))
    pages = pages.withColumn("sha", F.sha1(F.col("html").cast("binary")))
    # Only payloads that occur again are joined back, and without their bodies.
    first = pages.groupBy("sha").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("sha", "first_id", F.lit(True).alias("again"))
    # Which page revisits which is decided on keys; bodies move by page and payload, so that no payload is hot.
    found = pages.select("page_id", "sha").distinct().join(first, "sha")
    found = found.withColumnsRenamed({"page_id": "_page", "sha": "_sha"})
    return pages.join(found, F.col("page_id").eqNullSafe(F.col("_page")) & (F.col("sha") == F.col("_sha")), "left").drop("_page", "_sha")


def write_monolithic(pages: DataFrame, where: str) -> DataFrame:
    """One archive a partition, compressed as one stream; returns (file). Rows come from digested()."""
    fs, root = open_fs(where)
    fs.create_dir(f"{root}/mono")

    def run(batches):
        fs, root = open_fs(where)
        name = f"crawl-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex[:8]}.warc.gz"
        tool, out = zlib.compressobj(1, zlib.DEFLATED, 31), None
        for b in batches:
            for page_id, url, html, sha, first, again in zip(*(b.column(c).to_pylist() for c in ("page_id", "url", "html", "sha", "first_id", "again"))):
                if out is None:
                    out = fs.open_output_stream(f"{root}/mono/{name}")
                    out.write(tool.compress(record([("WARC-Type", "warcinfo"), ("WARC-Record-ID", record_id(None, TaskContext.get().partitionId())), ("WARC-Date", DATE)], b"")))
                is_first = not again or page_id == first
                out.write(tool.compress(page_record(page_id, url, html.encode("utf-8", "surrogatepass"), None if is_first else first, 0 if is_first else 1, base64.b32encode(bytes.fromhex(sha)).decode())))
        if out:
            out.write(tool.flush())
            out.close()
            yield pa.RecordBatch.from_pydict({"file": [name]})

    pages.mapInArrow(run, "file string").write.parquet(f"{where}/written")
    return pages.sparkSession.read.schema("file string").parquet(f"{where}/written")


def normalise_all(files: DataFrame, where: str) -> DataFrame:
    """Rewrite each file of `where`/mono below `where`/warc; returns the index (file, offset, length)."""
    fs, root = open_fs(where)
    fs.create_dir(f"{root}/warc")

    def run(batches):
        fs, root = open_fs(where)
        for b in batches:
            for name in b.column(0).to_pylist():
                new = f"{name.removesuffix('.warc.gz')}-{uuid.uuid4().hex[:6]}.warc.gz"
                with fs.open_input_stream(f"{root}/mono/{name}") as source, fs.open_output_stream(f"{root}/warc/{new}", compression=None) as sink, fs.open_output_stream(f"{root}/warc/{new}.idx") as sidecar:
                    places = normalise(source, sink, sidecar)
                off, n = zip(*places)
                yield pa.RecordBatch.from_arrays([pa.array([new] * len(off)), pa.array(off, pa.int64()), pa.array(n, pa.int64())], names=["file", "offset", "length"])

    # One file a task: the list of files is as long as the number of writers.
    files.repartition(max(1, files.count()), "file").mapInArrow(run, INDEX).write.parquet(f"{where}/index")
    return files.sparkSession.read.schema(INDEX).parquet(f"{where}/index")


def read(index: DataFrame, where: str) -> DataFrame:
    """Pages of the archives, member by member by the index; every digest is checked."""

    def run(batches):
        fs, root = open_fs(where)
        name, source = None, None
        for b in batches:
            rows = []
            for f, off, n in zip(*(b.column(c).to_pylist() for c in ("file", "offset", "length"))):
                if f != name:
                    name, source = f, fs.open_input_file(f"{root}/warc/{f}")
                source.seek(off)
                h, payload = parse(zlib.decompress(source.read(n), 31))
                kind = h["warc-type"]
                if kind == "warcinfo":
                    continue
                sha = h["warc-payload-digest"].removeprefix("sha1:")
                if kind == "response" and digest(payload) != sha:
                    raise ValueError(f"{f} at {off}: the payload differs from its digest")
                to = h.get("x-refers-to-page")
                rows.append((int(h["x-page-id"]) if h["x-page-id"] else None, int(h["x-payload-length"]), sha, kind, int(to) if to else None))
            cols = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()))], names=[x.split()[0] for x in RECORD.split(", ")])

    return index.mapInArrow(run, RECORD)


def op5_warc_normaliser(spark: SparkSession, sf_dir: str) -> DataFrame:
    where = scratch(spark, "warc")
    files = write_monolithic(digested(spark.read.parquet(f"{sf_dir}/pages.parquet")), where)
    index = normalise_all(files, where)
    return read(index, where)


ORACLE = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
d AS (SELECT page_id, octet_length(body) AS n, sha1(body) AS hex FROM p),
f AS (SELECT hex, min(page_id) AS first_id FROM d GROUP BY hex)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes,
       (SELECT string_agg(substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST(
            (instr('0123456789abcdef', substr(hex || '0', 1 + (5 * i) // 4, 1)) - 1) * 16 + instr('0123456789abcdef', substr(hex || '0', 2 + (5 * i) // 4, 1)) - 1 AS INTEGER)
            // CAST(power(2, 3 - (5 * i) % 4) AS INTEGER) % 32, 1), '' ORDER BY i) FROM range(32) t(i)) AS payload_digest,
       CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id <> first_id THEN first_id END AS refers_to
FROM d JOIN f USING (hex)
"""
__all__ = ["normalise", "normalise_all", "op5_warc_normaliser", "page_record", "parse", "read", "split", "write_monolithic"]
