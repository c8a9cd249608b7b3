"""Structured Streaming forms over the events and documents tables.

Each runs to the end of what is there (availableNow) and returns the sink's rows. A sentinel event far ahead closes the
windows in append mode where that is used.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from recmatch.operators import strategies as S
from recmatch.operators.judges import LENIENT
from recmatch.plans.blocking import block_tfidf
from recmatch.plans.candidates import compared, shared, side
from recmatch.plans.methods import query
from recmatch.plans.workloads import WORKLOADS
from recmatch.sources.tables import table


def _place(s: SparkSession, name: str) -> str:
    return f"{shared(s).rstrip('/')}/{name}-{uuid.uuid4().hex[:8]}"


def stream(s: SparkSession, d: str, name: str) -> DataFrame:
    """A table as a file stream. The files' schema comes from the batch reader."""
    schema = table(s, d, name).schema
    return s.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet").parquet(d) if not _is_folder(s, f"{d}/{name}.parquet") else s.readStream.schema(schema).parquet(f"{d}/{name}.parquet")


def _is_folder(s: SparkSession, path: str) -> bool:
    p = s.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(s.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def events(s: SparkSession, d: str) -> DataFrame:
    """Event times as timestamps: watermarks take no zone-free ones."""
    return stream(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def finish(df: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Run a streaming query over what is there into Parquet: complete batches replace one another, updates stay beside each other."""
    s, out = df.sparkSession, _place(df.sparkSession, name)

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/data/batch={0 if mode == 'complete' else n}")

    q = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.schema(df.schema).parquet(f"{out}/data/batch=*")


def sunk(df: DataFrame, name: str) -> DataFrame:
    """Run a streaming query in append mode into Parquet."""
    s, out = df.sparkSession, _place(df.sparkSession, name)
    q = df.writeStream.format("parquet").option("path", f"{out}/data").option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.schema(df.schema).parquet(f"{out}/data")


_sec = "cast(floor(epoch(ts)) as bigint)"


@query("st_tumbling", f"select event_type, {_sec} - {_sec} % 3600 as start, count(*) as n from events group by 1, 2")
def _(s, d):
    g = events(s, d).withWatermark("ts", "10 minutes").groupBy("event_type", F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return finish(g, "tumbling").select("event_type", F.unix_timestamp("window.start").alias("start"), "n")


@query("st_sliding", f"select event_type, {_sec} - {_sec} % 1800 - o * 1800 as start, count(*) as n from events, (values (0), (1)) v(o) group by 1, 2")
def _(s, d):
    g = events(s, d).withWatermark("ts", "10 minutes").groupBy("event_type", F.window("ts", "1 hour", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return finish(g, "sliding").select("event_type", F.unix_timestamp("window.start").alias("start"), "n")


@query("st_session", "select user_id, count(*) as n from (select user_id, ts, sum(new) over (partition by user_id order by ts, event_id) as k from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 20 minute then 0 else 1 end as new from events) a) b group by user_id, k")
def _(s, d):
    g = events(s, d).withWatermark("ts", "10 minutes").groupBy("user_id", F.session_window("ts", "20 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return finish(g, "session").select("user_id", "n")


@query("st_dedup", "select user_id, event_type, count(*) as n from (select distinct event_id, user_id, event_type from events) q group by 1, 2")
def _(s, d):
    e = events(s, d).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")
    return sunk(e, "dedup").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))


@query("st_static_join", "select event_id, c_name from events join customer on user_id = c_custkey")
def _(s, d):
    return sunk(events(s, d).join(table(s, d, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"), "static")


@query("st_stream_join", "select a.event_id as seen, b.event_id as clicked from events a join events b on a.user_id = b.user_id where a.event_type = 'view' and b.event_type = 'click' and b.ts >= a.ts and b.ts <= a.ts + interval 10 minute")
def _(s, d):
    a = events(s, d).filter("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("seen"), F.col("ts").alias("x")).withWatermark("x", "30 minutes")
    b = events(s, d).filter("event_type = 'click'").select(F.col("user_id").alias("v"), F.col("event_id").alias("clicked"), F.col("ts").alias("y")).withWatermark("y", "30 minutes")
    return sunk(a.join(b, F.expr("u = v and y >= x and y <= x + interval 10 minutes")).select("seen", "clicked"), "linked")


@query("st_incremental_match")
def incremental(s, d):
    """Benchmark items that arrive as files get decisions against the standing documents, batch by batch."""
    w, out = WORKLOADS["w4"], _place(s, "decided")
    d2 = side(s, d, w, "d2")

    def decide(batch: DataFrame, n: int) -> None:
        d1 = batch.select(F.col("item_id").alias("rid"), "text")
        c = compared(block_tfidf(d1, d2, w), d1, d2, w).withColumn("is_true", F.lit(False))
        S.compound(c, LENIENT, LENIENT).write.mode("overwrite").parquet(f"{out}/batch={n}")

    q = stream(s, d, "benchmark").writeStream.foreachBatch(decide).option("checkpointLocation", _place(s, "state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.schema("anchor_id long, choice int, cand_id long").parquet(f"{out}/batch=*")


@query("st_stateful_canon", "select user_id, min(event_id) as canonical, count(*) as n from events group by user_id")
def _(s, d):
    """The first id seen of each key, kept as state that ends after a day of event time without events."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def run(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        import pandas as pd

        best, n = state.get if state.exists else (2**62, 0)
        last = state.getCurrentWatermarkMs()
        for f in frames:
            best, n, last = min(best, int(f["event_id"].min())), n + len(f), max(last, int(f["ts"].max().timestamp() * 1000))
        state.update((best, n))
        state.setTimeoutTimestamp(last + 86_400_000)
        yield pd.DataFrame({"user_id": [key[0]], "canonical": [best], "n": [n]})

    g = events(s, d).withWatermark("ts", "1 hour").select("user_id", "event_id", "ts").groupBy("user_id").applyInPandasWithState(run, "user_id long, canonical long, n long", "best long, n long", "update", GroupStateTimeout.EventTimeTimeout)
    out = finish(g, "canon", "update")
    return out.groupBy("user_id").agg(F.min("canonical").alias("canonical"), F.max("n").alias("n"))


@query("st_late_data")
def late(s, d):
    """Hourly counts in append mode: a window is given out once the watermark has passed it; later rows are dropped."""
    g = events(s, d).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return sunk(g.select(F.unix_timestamp("window.start").alias("start"), "n"), "late")
