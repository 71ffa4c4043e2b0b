"""Streams of crawl events: windows, late rows, duplicates, joins, a sample of fixed size per stratum, running prevalence.

Each query drives a stream over given files to its end and returns what its sink holds, so batch SQL can check it.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from geocensus.functions.columns import order_key
from geocensus.operators import study as Y
from geocensus.plans import workloads as W
from geocensus.sources import index as I

Query = Callable[[SparkSession, str], DataFrame]


def _arrivals(s: SparkSession, sf_dir: str, name: str = "events", files: int = 1) -> DataFrame:
    """A table as a stream of files in the shared folder, one file a trigger."""
    src = I.table(s, sf_dir, name)
    path = I.scratch(s, f"arrivals-{name}")
    src.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path) if files > 1 else src.coalesce(1).write.parquet(path)
    return _timed(s.readStream.schema(src.schema).option("maxFilesPerTrigger", 1).parquet(path))


def _timed(df: DataFrame) -> DataFrame:
    """``ts`` as a timestamp with a zone, which watermarks need."""
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def _files(s: SparkSession, path: str, like: DataFrame) -> DataFrame:
    return _timed(s.readStream.schema(like.schema).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(path))


def _drained(df: DataFrame, mode: str, key: str | None = None) -> DataFrame:
    """Runs a stream to its end; its rows, written per batch to the shared folder."""
    s = df.sparkSession
    out, check = I.scratch(s, "stream-out"), I.scratch(s, "stream-check")
    n = "sink_" + uuid.uuid4().hex[:8]

    def keep(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={i}")  # a replayed batch overwrites itself

    q = df.writeStream.outputMode(mode).queryName(n).option("checkpointLocation", check).trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    rows = s.read.schema(T.StructType([*df.schema.fields, T.StructField("batch", T.IntegerType())])).option("basePath", out).parquet(out)
    if mode == "append":
        return rows.drop("batch")
    return rows.groupBy(key).agg(*[F.max_by(c, "batch").alias(c) for c in df.columns if c != key])


def tumbling(s: SparkSession, d: str) -> DataFrame:
    e = _arrivals(s, d, files=4).withWatermark("ts", "40 days")
    g = e.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return _drained(g.select(F.concat_ws("|", F.col("window.start").cast("string"), "event_type").alias("key"), "n"), "update", "key")


def sliding(s: SparkSession, d: str) -> DataFrame:
    e = _arrivals(s, d, files=4).withWatermark("ts", "40 days")
    g = e.groupBy(F.window("ts", "1 day", "12 hours")).agg(F.count("*").alias("n"))
    return _drained(g.select(F.col("window.start").cast("string").alias("key"), "n"), "update", "key")


def session(s: SparkSession, d: str) -> DataFrame:
    """Sessions of a user, closed by six hours of silence; a last far row moves the watermark past all of them."""
    e = I.table(s, d, "events").select("user_id", "ts")
    end = e.agg(F.max("ts").alias("m")).select(F.lit(-1).cast("long").alias("user_id"), (F.col("m") + F.expr("interval 90 days")).alias("ts"))
    path = I.scratch(s, "sessions")
    e.coalesce(1).write.parquet(f"{path}/a")
    end.write.parquet(f"{path}/b")
    stream = _files(s, path, e).withWatermark("ts", "40 days")
    g = stream.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return _drained(g.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n"), "append").where("user_id >= 0")


def late_rows(s: SparkSession, d: str) -> DataFrame:
    """Rows older than the watermark when they arrive are dropped: a second file repeats the first day and adds nothing."""
    e = I.table(s, d, "events").select("event_id", "ts")
    lo = e.agg(F.min(F.date_trunc("day", "ts")).alias("lo"))
    path = I.scratch(s, "late")
    e.coalesce(1).write.parquet(f"{path}/a")
    # The filter on late rows follows the watermark by one batch, so one row goes between.
    e.orderBy(F.desc("ts"), "event_id").limit(1).coalesce(1).write.parquet(f"{path}/between")
    late = e.join(F.broadcast(lo), F.date_trunc("day", "ts") == F.col("lo")).select("event_id", "ts")
    late.coalesce(1).write.parquet(f"{path}/b")
    stream = _files(s, path, e).withWatermark("ts", "1 hour")
    g = stream.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return _drained(g.select(F.col("window.start").cast("timestamp_ntz").alias("day"), "n"), "append")


def dedup(s: SparkSession, d: str) -> DataFrame:
    e = I.table(s, d, "events").select("event_id", "ts")
    path = I.scratch(s, "twice")
    e.coalesce(1).write.parquet(f"{path}/a")
    e.where("event_id % 2 = 0").coalesce(1).write.parquet(f"{path}/b")
    stream = _files(s, path, e)
    return _drained(stream.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append")


def static_join(s: SparkSession, d: str) -> DataFrame:
    c = I.table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return _drained(_arrivals(s, d, files=2).join(c, "user_id").select("event_id", "c_mktsegment"), "append")


def stream_join(s: SparkSession, d: str) -> DataFrame:
    """Requests and responses of a user within an hour; even ids stand for requests, odd ones for responses."""
    e = _arrivals(s, d, files=2).select("event_id", "user_id", "ts").withWatermark("ts", "40 days")
    a = e.where("event_id % 2 = 0").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    f = _arrivals(s, d, files=2).select("event_id", "user_id", "ts").withWatermark("ts", "40 days").where("event_id % 2 = 1").select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("r"))
    return _drained(a.join(f, F.expr("u = v and r >= t and r <= t + interval 1 hour")).select("a", "b"), "append")


def bottom_k(s: SparkSession, d: str, k: int = 20) -> DataFrame:
    """The ``k`` smallest hashes per stratum, kept as state: the batch sample, whatever the order of arrival."""
    e = _arrivals(s, d, files=3).select("event_type", "event_id", order_key("s1", "event_id").alias("h"))

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(zip(*state.get, strict=True)) if state.exists else []
        for f in frames:
            held = sorted([*held, *zip(f["h"], f["event_id"].astype(int), strict=True)])[:k]
        state.update(([h for h, _ in held], [int(i) for _, i in held]))
        yield pd.DataFrame({"event_type": [key[0]], "ids": [",".join(str(i) for _, i in held)]})

    out = e.groupBy("event_type").applyInPandasWithState(step, "event_type string, ids string", "h array<string>, i array<long>", "update", GroupStateTimeout.NoTimeout)
    return _drained(out, "update", "event_type").select("event_type", F.explode(F.split("ids", ",")).alias("x")).select("event_type", F.col("x").cast("long").alias("event_id"))


def running_prevalence(s: SparkSession, d: str) -> DataFrame:
    """Planted pages arrive in files; flags are found as they come, and each batch's counts are merged by release into a table.

    A batch writes under its own number, so one that runs again after a failure replaces itself.
    """
    pages = W.planted_pages(s, d).select("page_id", "html", "release")
    path, counts, state = I.scratch(s, "arrivals-pages"), I.scratch(s, "stream-prevalence"), I.scratch(s, "stream-state")
    pages.repartitionByRange(4, "page_id").write.parquet(path)
    arriving = s.readStream.schema(pages.schema).option("maxFilesPerTrigger", 1).parquet(path)

    def merge(batch: DataFrame, n: int) -> None:
        f = Y.doc_flags(batch, "html", ["release"])
        a, c = F.col("has_addr"), F.col("has_coord")
        f.groupBy("release").agg(F.count("*").alias("n"), F.count_if(a | c).alias("x_any"), F.count_if(a).alias("x_addr"), F.count_if(c).alias("x_coord"), F.count_if(a & c).alias("x_both")).write.mode("overwrite").parquet(f"{counts}/batch={n}")

    arriving.writeStream.foreachBatch(merge).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    told = s.read.schema("release string, n long, x_any long, x_addr long, x_coord long, x_both long, batch int").parquet(counts)
    return told.groupBy("release").agg(*[F.sum(x).alias(x) for x in ("n", "x_any", "x_addr", "x_coord", "x_both")])


_QUERIES: dict[str, tuple[Query, str | None]] = {
    "stream_tumbling": (tumbling, "select strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') || '|' || event_type as key, count(*) as n from events group by 1"),
    "stream_sliding": (sliding, "select strftime(w, '%Y-%m-%d %H:%M:%S') as key, count(*) as n from (select unnest([time_bucket(interval 12 hour, ts, timestamp '2023-01-01'), time_bucket(interval 12 hour, ts, timestamp '2023-01-01') - interval 12 hour]) as w from events) group by 1"),
    "stream_session": (session, "select user_id, min(ts) as start, count(*) as n from (select *, sum(new) over (partition by user_id order by ts, event_id) as k from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 6 hour then 0 else 1 end as new from events)) group by user_id, k"),
    "stream_watermark_late": (late_rows, "select day, n from (select date_trunc('day', ts)::timestamp as day, count(*) as n from events group by 1) where day + interval 1 day <= (select max(ts) - interval 1 hour from events)"),
    "stream_dedup": (dedup, "select event_id from events"),
    "stream_static_join": (static_join, "select event_id, c_mktsegment from events join customer on user_id = c_custkey"),
    "stream_stream_join": (stream_join, "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour where a.event_id % 2 = 0 and b.event_id % 2 = 1"),
    "stream_bottom_k": (bottom_k, "select event_type, event_id from (select *, row_number() over (partition by event_type order by md5('s1|' || event_id), event_id) as nth from events) where nth <= 20"),
    "stream_prevalence": (running_prevalence, f"with {W.PAGE_FLAGS} select release, {W.COUNTS} from f group by 1"),
}


def queries() -> dict[str, Query]:
    return {k: f for k, (f, _) in _QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for k, (_, q) in _QUERIES.items() if q}
