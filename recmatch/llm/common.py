"""What the operators share: the cluster's shared folder, Arrow mapping, word splitting."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import sys
import uuid
from collections.abc import Callable, Iterator
from contextvars import ContextVar

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The characters that end a word.
BLANKS = "\t\n\x0b\x0c\r"


#: Arrow batches, where the session has Spark's defaults: setting, default, value. Executors hold several at once, beside their heap.
BATCHES = (("spark.sql.execution.arrow.maxRecordsPerBatch", "10000", "2000"), ("spark.sql.execution.arrow.maxBytesPerBatch", "67108864b", "16777216b"))


def small_batches(spark: SparkSession) -> None:
    """Batches of 2000 rows and 16 MB at most, unless the session says otherwise."""
    for key, default, value in BATCHES:
        if spark.conf.get(key, None) in (None, default):
            spark.conf.set(key, value)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as a URI; one is set only where none is."""
    small_batches(spark)
    sc = spark.sparkContext
    where = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not where:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        where = "file:///tmp/recmatch-shared"
        sc.setCheckpointDir(where)
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(where)
    return where if ":/" in where else f"file://{where}"


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder's path below the shared one."""
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


#: Where the folders of stored tables are noted, if somebody wants to delete them later.
_noted: ContextVar[list[str] | None] = ContextVar("noted", default=None)


@contextlib.contextmanager
def noting() -> Iterator[list[str]]:
    """Collects the folders of the tables that are stored inside and outlive it."""
    mine: list[str] = []
    token = _noted.set(mine)
    try:
        yield mine
    finally:
        _noted.reset(token)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write a table in the shared folder and read it back: cuts lineage, survives lost executors."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    if (noted := _noted.get()) is not None:
        noted.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def settled(spark: SparkSession, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """make(), stored. The tables that make() stored on the way are deleted: nothing reads them any more."""
    with noting() as mine:
        try:
            path = scratch(spark, name)
            df = make()
            df.write.parquet(path)
        finally:
            for p in mine:
                dropped(spark, p)
    rested(spark)
    if (noted := _noted.get()) is not None:
        noted.append(path)
    return spark.read.schema(df.schema).parquet(path)


def swept(docs: DataFrame, folders: list[str]) -> None:
    """Delete the folders that docs does not read, and take them off the list; let Spark clean up the shuffles nobody can read."""
    spark = docs.sparkSession
    files = docs.inputFiles() if folders else []
    for path in [p for p in folders if not any(p.rsplit("/", 1)[1] in f for f in files)]:
        dropped(spark, path)
        folders.remove(path)
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    rested(spark)


def rested(spark: SparkSession) -> None:
    """Have executors collect their garbage: a JVM keeps the heap that a stage once needed, and Python workers need the memory next.

    A task a core, so that all executors get some; one that gets none keeps its heap, and results do not depend on it.
    """
    sc = spark.sparkContext
    n = 1 if sc.master == "local" or sc.master.startswith("local[") else sc.defaultParallelism
    spark.range(0, n, 1, n).select(F.expr("reflect('java.lang.System', 'gc')")).write.format("noop").mode("overwrite").save()


def numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """docs, stored, with a number of each row, and that column's name, which no other column begins with. Tells rows apart that share an id."""
    row = "_row"
    while any(c.lower().startswith(row) for c in docs.columns):
        row += "_"
    return stored(docs.withColumn(row, F.monotonically_increasing_id()), "rows"), row


def without(docs: DataFrame, row: str, gone: DataFrame) -> DataFrame:
    """numbered() docs without the rows of a stored one-column table, and without the number."""
    return docs.join(gone.select(F.col(gone.columns[0]).alias(f"{row}_")), F.col(row) == F.col(f"{row}_"), "left_anti").drop(row)


def dropped(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared one, by Hadoop's file system."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def open_fs(uri: str):
    """(file system, path) for Python tasks."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def words_of(text: str) -> list[str]:
    """Runs of characters other than space, tab, line feed, vertical tab, form feed, carriage return."""
    for c in BLANKS:
        if c in text:
            text = text.replace(c, " ")
    return [w for w in text.split(" ") if w]


def ascii_lower(text: str) -> str:
    """Lower-case A-Z only."""
    if text.isascii():
        return text.lower()
    return text.translate(_LOWER)


_LOWER = {c: c + 32 for c in range(65, 91)}


def kept_in_worker(key: str, make):
    """A value that lives in the Python worker until another operator wants one: tokenizers, word caches. Workers outlive stages."""
    store = sys.__dict__.setdefault("_recmatch_kept", {})
    if key not in store:
        released()
        store[key] = make()
    return store[key]


def released() -> None:
    """Give back what earlier operators left in this Python worker, to the system too where that is possible."""
    sys.__dict__.get("_recmatch_kept", {}).clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other systems have no such call
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def tidy(run):
    """run, a function of a task's batches, that gives back its memory when the task ends: idle workers keep what they hold."""

    def tidied(batches):
        released()
        try:
            yield from run(batches)
        finally:
            released()

    return tidied


def cut_up(batches, rows: int = 1000):
    """Batches of fewer rows, which take less memory as Python objects."""
    for b in batches:
        for i in range(0, len(b), rows):
            yield b.slice(i, rows)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def spread(df: DataFrame, *keys: str) -> DataFrame:
    return df.repartition(*[F.col(k) for k in keys])
