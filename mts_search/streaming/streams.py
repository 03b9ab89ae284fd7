"""Structured Streaming: channel aggregates with watermarks, deduplication, window tails as state, monitoring, append sink, interval join."""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..session import shared_folder

EVENT_SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_each: int = 4) -> DataFrame:
    """Events from a folder of Parquet files; ``ts`` must be a timestamp (a watermark needs one)."""
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_each).parquet(path)


def split_events(events: DataFrame, path: str, files: int = 10) -> None:
    """The events as files in order of time, to play them as a stream."""
    events.withColumn("ts", F.col("ts").cast("timestamp")).select(*[c.split()[0] for c in EVENT_SCHEMA.split(", ")]).repartitionByRange(files, "ts").write.mode("overwrite").parquet(path)
    date_files(events.sparkSession, path)


def date_files(spark: SparkSession, path: str) -> None:
    """Modification times of a folder's files in order of their names, a second apart.

    A file stream takes files by modification time. Tasks end in any order, and a file that comes too late is behind the
    watermark, where its rows would be dropped.
    """
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark._jsc.hadoopConfiguration())
    listed = lambda: {f.getPath().getName(): f for f in fs.listStatus(where) if f.getPath().getName().startswith("part-")}
    names = sorted(listed())
    now = int(time.time()) * 1000
    for i, name in enumerate(names):
        fs.setTimes(spark._jvm.org.apache.hadoop.fs.Path(where, name), now - (len(names) - i) * 1000, -1)
    found = listed()
    dates = [found[name].getModificationTime() for name in names]
    if any(a >= b for a, b in zip(dates, dates[1:], strict=False)):
        raise OSError(f"the file system of {path} doesn't keep modification times, so a stream can't play its files in order")


def tumbling(stream: DataFrame, width: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("cents")).select(F.unix_seconds("window.start").alias("start_s"), "event_type", "n", "cents")


def sliding(stream: DataFrame, width: str = "1 hour", step: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("window.start").alias("start_s"), "n")


def sessions(stream: DataFrame, gap: str = "6 hours", late: str = "10 minutes") -> DataFrame:
    """A row exactly ``gap`` after the last begins a session; Spark would still add it, so its gap is a microsecond shorter."""
    return stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", f"{gap} -1 microsecond")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_seconds("session_window.start").alias("start_s"), "n")


def deduplicated(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def pairs_within(a: DataFrame, b: DataFrame, span: str = "1 hour") -> DataFrame:
    """Stream-stream join: events of one user and two types, the second within ``span`` after the first.

    The state of a key is read as a whole for each row, so keys are a user's stretches of ``span``: a second event is
    looked for in the stretch of its own time and in the one before, and a first event lies in one of them only.
    """
    k = F.expr(f"unix_micros(ts) div unix_micros(timestamp_micros(0) + interval {span})")
    x = a.withWatermark("ts", span).select(F.col("user_id").alias("u1"), k.alias("k1"), F.col("ts").alias("t1"), F.col("event_id").alias("first_id"))
    y = b.withWatermark("ts", span).select(F.col("user_id").alias("u2"), F.explode(F.array(k, k - 1)).alias("k2"), F.col("ts").alias("t2"), F.col("event_id").alias("second_id"))
    return x.join(y, F.expr(f"u1 = u2 and k1 = k2 and t2 >= t1 and t2 <= t1 + interval {span}")).select("first_id", "second_id")


def tail_features(points: DataFrame, q: int, kept: list[int]) -> DataFrame:
    """Features of each window as its last point comes: the state of a series is its last q-1 values.

    ``points`` is a stream of (series_id, t, v); a series' points must come in order of t within and across batches.
    """
    dims = K.dims_of(q, {0: kept})

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held_t, held = (list(x) for x in state.get) if state.exists else ([], [])
        got = pd.concat(list(batches)).sort_values("t")
        t, v = [*held_t, *got["t"].tolist()], [*held, *got["v"].tolist()]
        f = K.sliding_features(np.array([v], float), q, dims)
        state.update((t[-(q - 1) :], v[-(q - 1) :]))
        if len(f):
            yield pd.DataFrame({"series_id": key[0], "start": t[: len(f)], "features": [[float(x) for x in r] for r in f]})

    return points.groupBy("series_id").applyInPandasWithState(step, "series_id bigint, start bigint, features array<double>", "t array<bigint>, v array<double>", "append", "NoTimeout")


def monitor(features: DataFrame, references: DataFrame, radius: float) -> DataFrame:
    """Alerts: new windows whose feature distance (a lower bound) to a fixed reference is within the radius; references are few."""
    gap = F.aggregate(F.zip_with("features", "reference", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    return features.crossJoin(F.broadcast(references)).withColumn("bound", F.sqrt(gap)).where(F.col("bound") <= radius)


def append_sink(stream: DataFrame, path: str, checkpoint: str):
    """Each batch in a folder of its own number: a repeated batch overwrites itself."""
    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that is there now through the stream into a Parquet table in the shared folder; the checkpoint is beside it.

    ``append``: every batch under its number, so that a repeated batch overwrites itself. ``complete``: the last
    batch is the result.
    """
    spark = stream.sparkSession
    at = f"{shared_folder(spark)}/stream_{uuid.uuid4().hex}"
    last: list[int] = []

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={number}")
        last.append(number)

    stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{at}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    if not last:
        return spark.createDataFrame([], stream.schema)
    found = spark.read.schema(stream.schema).parquet(f"{at}/out/batch={max(last)}" if mode == "complete" else f"{at}/out")
    return found.select(*stream.columns)


def played(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_folder(spark)}/events_{uuid.uuid4().hex}"
    split_events(spark.read.parquet(f"{sf_dir}/events.parquet"), folder)
    return event_stream(spark, folder)


def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly channels through a stream, complete mode: equal to the batch twin."""
    return run_to_table(tumbling(played(spark, sf_dir)), "complete").select("start_s", "event_type", "n")


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(sliding(played(spark, sf_dir)), "complete")


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(sessions(played(spark, sf_dir)), "complete")


def stream_late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts of a stream whose last file brings the first five days again: behind the watermark, so not counted.

    A batch drops what is behind the watermark that the batch before it began with, so two files go before the late one.
    """
    folder = f"{shared_folder(spark)}/late_{uuid.uuid4().hex}"
    e = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).select(*[c.split()[0] for c in EVENT_SCHEMA.split(", ")])
    for i, part in enumerate(("ts < timestamp'2024-01-20'", "ts >= timestamp'2024-01-20'", "ts < timestamp'2024-01-06'")):
        e.where(part).coalesce(1).write.parquet(f"{folder}/part={i}")
    s = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder)
    counts = s.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return run_to_table(counts.select(F.unix_seconds("window.start").alias("start_s"), "n"))


def stream_append_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events through the append sink, played twice with one checkpoint: every event once."""
    at = f"{shared_folder(spark)}/sink_{uuid.uuid4().hex}"
    split_events(spark.read.parquet(f"{sf_dir}/events.parquet"), f"{at}/in")
    for _ in range(2):
        append_sink(event_stream(spark, f"{at}/in").select("event_id", "user_id"), f"{at}/out", f"{at}/checkpoint").awaitTermination()
    return spark.read.parquet(f"{at}/out").select("event_id", "user_id")


def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = played(spark, sf_dir)
    return run_to_table(deduplicated(s.union(s))).select("event_id")


def stream_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = played(spark, sf_dir)
    return run_to_table(pairs_within(s.where("event_type = 'click'"), s.where("event_type = 'purchase'")))


def _hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """720 hourly counts as a stream of points in order."""
    folder = f"{shared_folder(spark)}/points_{uuid.uuid4().hex}"
    e = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy(F.floor(F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)") / 3600).alias("t")).agg(F.count(F.lit(1)).cast("double").alias("v"))
    spark.range(720).select(F.lit(0).cast("bigint").alias("series_id"), F.col("id").alias("t")).join(e, "t", "left").select("series_id", "t", F.coalesce("v", F.lit(0.0)).alias("v")).coalesce(1).sortWithinPartitions("t").write.parquet(folder)
    return spark.readStream.schema("series_id bigint, t bigint, v double").parquet(folder)


def stream_tail_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of 24 daily-hour counts completed by a stream of 720 points in order."""
    got = run_to_table(tail_features(_hours(spark, sf_dir), 24, [0, 1]))
    return got.select("series_id", "start", F.round(F.get("features", F.lit(0)), 4).alias("mean_feature"))


def stream_monitor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Alerts of windows of 24 hours whose mean feature lies within 2 of that of a flat reference of 14 an hour."""
    reference = spark.createDataFrame([(0, [14.0 * 24**0.5])], "reference_id int, reference array<double>")
    got = run_to_table(monitor(tail_features(_hours(spark, sf_dir), 24, [0]), reference, 2.0))
    return got.select("series_id", "start", "reference_id", F.round("bound", 4).alias("bound"))


HOUR = "cast(floor(datediff('second', timestamp '2024-01-01', ts) / 3600) as bigint)"
_ALL = {
    "stream_tumbling": (stream_tumbling, "select cast(epoch(time_bucket(interval '1 hour', ts)) as bigint) as start_s, event_type, count(*) as n from events group by 1, 2"),
    "stream_sliding": (stream_sliding, "select s as start_s, count(*) as n from (select unnest([cast(floor(epoch(ts) / 1800) as bigint) * 1800, cast(floor(epoch(ts) / 1800) as bigint) * 1800 - 1800]) as s from events) group by 1"),
    "stream_sessions": (stream_sessions, "with e as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval '6 hours' or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events), s as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from e) select user_id, cast(floor(epoch(min(ts))) as bigint) as start_s, count(*) as n from s group by user_id, k"),
    "stream_late_rows": (stream_late_rows, "select h as start_s, count(*) as n from (select cast(epoch(time_bucket(interval '1 hour', ts)) as bigint) as h from events) group by 1 having h + 3600 <= (select epoch(max(ts)) - 600 from events)"),
    "stream_append_sink": (stream_append_sink, "select event_id, user_id from events"),
    "stream_dedup": (stream_dedup, "select event_id from events"),
    "stream_pairs": (stream_pairs, "select a.event_id as first_id, b.event_id as second_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval '1 hour'"),
    "stream_tail_state": (stream_tail_state, f"with h as (select cal.t, coalesce(a.n, 0) as n from (select unnest(range(0, 720)) as t) cal left join (select {HOUR} as t, count(*) as n from events group by 1) a using (t)) select cast(0 as bigint) as series_id, cast(t as bigint) as start, round(s / sqrt(24.0), 4) as mean_feature from (select t, sum(n) over w as s, count(*) over w as c from h window w as (order by t rows between current row and 23 following)) where c = 24"),
    "stream_monitor": (stream_monitor, f"with h as (select cal.t, coalesce(a.n, 0) as n from (select unnest(range(0, 720)) as t) cal left join (select {HOUR} as t, count(*) as n from events group by 1) a using (t)) select cast(0 as bigint) as series_id, cast(t as bigint) as start, cast(0 as integer) as reference_id, round(abs(s / sqrt(24.0) - 14.0 * sqrt(24.0)), 4) as bound from (select t, sum(n) over w as s, count(*) over w as c from h window w as (order by t rows between current row and 23 following)) where c = 24 and abs(s / sqrt(24.0) - 14.0 * sqrt(24.0)) <= 2"),
}
QUERIES = {k: v[0] for k, v in _ALL.items()}
ORACLE_SQL = {k: v[1] for k, v in _ALL.items()}
