"""The event stream: windows, late rows, joins and state, each equal to the batch result once the stream is drained.

Sinks write a micro-batch under its own number, so that a repeated batch replaces itself (exactly once). ``ts`` comes
without a zone and is read as UTC by the session's zone setting; sessions elsewhere shift all windows alike.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..operators.triangles import count_of_classes, owned_sets, set_classes
from ..sources.graphs import coact_pairs
from ..storage import shared_dir, spill

EVENT = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
DELAY = "10 minutes"


def _folder(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")


def replay(rows: DataFrame, parts: int, folder: str | None = None) -> str:
    """A folder of ``parts`` files in time order: what a stream of these rows leaves behind (a fixture, not an operator)."""
    folder = folder or _folder(rows.sparkSession)
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    low, high = rows.agg(F.min(us), F.max(us)).first()
    part = F.lit(0) if low is None else F.expr(f"(unix_micros(cast(ts as timestamp)) - {low}) * {parts} div {high - low + 1}")
    for k in range(parts):
        rows.where(part == k).coalesce(1).write.mode("append").parquet(folder)
    return folder


def stream(spark: SparkSession, folder: str, watermark: str | None = DELAY) -> DataFrame:
    """The folder as a stream of one file at a time, with event time."""
    got = spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))
    return got.withWatermark("ts", watermark) if watermark else got


def drain(rows: DataFrame, mode: str, keys: list[str] | None = None, folder: str | None = None, each: Callable | None = None) -> DataFrame:
    """All that the stream gives: its appended rows, or the last row of each key. ``folder`` keeps a run's checkpoint."""
    spark = rows.sparkSession
    folder = folder or _folder(spark)

    def put(batch: DataFrame, n: int) -> None:
        (each(batch) if each else batch).withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{folder}/out/slice={n}")

    query = rows.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    drain.progress = query.recentProgress
    out = spark.read.option("mergeSchema", "false").parquet(f"{folder}/out").drop("slice")
    if mode == "complete":
        last = out.agg(F.max("batch")).first()[0]
        return out.where(F.col("batch") == last).drop("batch")
    if keys:
        rest = [c for c in out.columns if c not in (*keys, "batch")]
        newest = out.groupBy(*keys).agg(F.max(F.struct("batch", *rest)).alias("x"))
        return newest.select(*keys, *[f"x.{c}" for c in rest])
    return out.drop("batch")


def _start(column: str = "window"):
    return F.unix_timestamp(f"{column}.start").alias("bucket")


def acts(spark: SparkSession, sf_dir: str, parts: int = 3) -> DataFrame:
    """(bucket, event_type, user_id, n) of hourly windows, from the drained stream."""
    s = stream(spark, replay(_events(spark, sf_dir).select("ts", "user_id", "event_type"), parts))
    counts = s.groupBy(F.window("ts", "60 minutes"), "event_type", "user_id").agg(F.count("*").alias("n"))
    return drain(counts.select(_start(), "event_type", "user_id", "n"), "update", ["bucket", "event_type", "user_id"])


def coact_edges(found: DataFrame) -> DataFrame:
    """(src, dst, n): pairs of events of two users that share window and type."""
    return coact_pairs(found.withColumnRenamed("bucket", "w"))


def ss_tumbling_coact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return coact_edges(acts(spark, sf_dir)).select("src", "dst", F.expr("1000000 div n").alias("weight"))


def ss_sliding_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = stream(spark, replay(_events(spark, sf_dir), 3))
    counts = s.groupBy(F.window("ts", "60 minutes", "15 minutes"), "event_type").agg(F.count("*").alias("events"))
    return drain(counts.select(_start(), "event_type", "events"), "update", ["bucket", "event_type"])


def ss_session_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions end after 30 minutes without an event of the user."""
    s = stream(spark, replay(_events(spark, sf_dir), 2))
    counts = s.groupBy(F.session_window("ts", "30 minutes").alias("window"), "user_id").agg(F.count("*").alias("events"))
    return drain(counts.select("user_id", F.unix_micros("window.start").alias("began"), "events"), "complete")


def ss_late_dropped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(events, dropped): events counted by closed windows, and rows behind the watermark, when the first tenth of the
    events comes once more after all others. Rows are counted after map-side aggregation, one for each late group."""
    rows = _events(spark, sf_dir)
    folder = replay(rows, 3)
    first = rows.agg(F.min("event_id"), F.max("event_id")).first()
    rows.where(F.col("event_id") <= first[0] + (first[1] - first[0]) // 10).coalesce(1).write.mode("append").parquet(folder)
    counts = stream(spark, folder).groupBy(F.window("ts", "60 minutes")).agg(F.count("*").alias("events"))
    total = drain(counts, "append").agg(F.sum("events").alias("events"))
    dropped = sum(o["numRowsDroppedByWatermark"] for p in drain.progress for o in p["stateOperators"])
    return total.select("events", F.lit(dropped).cast("bigint").alias("dropped"))


def ss_dedup_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event is sent twice within the delay; one stays."""
    rows = _events(spark, sf_dir)
    s = stream(spark, replay(rows.unionAll(rows), 1))
    return drain(s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "append")


def ss_stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    cust = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    s = stream(spark, replay(_events(spark, sf_dir), 2), None)
    return drain(s.join(cust, "user_id").groupBy("c_nationkey", "event_type").agg(F.count("*").alias("events")), "complete")


def ss_stream_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases at most ten minutes after a click of the same user; state is bounded by both watermarks."""
    folder = replay(_events(spark, sf_dir), 3)
    clicks = stream(spark, folder).where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    bought = stream(spark, folder).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    met = clicks.join(bought, F.expr("cu = pu and pt >= ct and pt <= ct + interval 10 minutes"))
    return drain(met.select("click", "purchase"), "append")


def _running(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    n, last = state.get if state.exists else (0, 0)
    for pdf in batches:
        n, last = n + len(pdf), max(last, int(pdf["event_id"].max()))
    state.update((n, last))
    yield pd.DataFrame({"user_id": [key[0]], "events": [n], "last_event": [last]})


def ss_state_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A running count of each user, kept as state of our own."""
    s = stream(spark, replay(_events(spark, sf_dir), 3), None).select("user_id", "event_id")
    kept = s.groupBy("user_id").applyInPandasWithState(_running, "user_id bigint, events bigint, last_event bigint", "n bigint, last bigint", "update", "NoTimeout")
    return drain(kept, "update", ["user_id"])


def ss_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(comp, users): components kept up to date: each batch joins its new users and windows to the labels so far.

    A batch links users and (window, type) pairs they acted in, so no pairs of users are formed; only labels are carried.
    """
    held: dict = {"labels": None}

    def each(batch: DataFrame) -> DataFrame:
        place = F.xxhash64(F.date_trunc("hour", "ts"), "event_type")
        links = batch.select(F.col("user_id").alias("src"), (-1 - F.pmod(place, F.lit((1 << 62) - 1))).alias("dst")).distinct()
        if held["labels"] is not None:
            links = links.unionByName(held["labels"].select(F.col("vid").alias("src"), F.col("comp").alias("dst")))
        held["labels"] = spill(connected_components(links))
        return batch.agg(F.count("*").alias("rows"))

    drain(stream(spark, replay(_events(spark, sf_dir), 3), None), "append", each=each)
    users = held["labels"].where("vid >= 0")
    least = users.groupBy("comp").agg(F.min("vid").alias("least"), F.count("*").alias("users"))
    return least.select(F.col("least").alias("comp"), "users")


def ss_window_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(bucket, triangles) of the users that act alike in each hour."""
    found = acts(spark, sf_dir, 1)
    return window_triangles(found)


def window_triangles(found: DataFrame) -> DataFrame:
    """(bucket, triangles) of acts (bucket, event_type, user_id): users that act alike in a window.

    Users of a window with one set of types count as one vertex with a weight: no pair of them is formed.
    """
    members = found.where("bucket is not null and event_type is not null").select(F.col("user_id").alias("vid"), F.col("bucket").alias("sg"), F.struct("bucket", "event_type").alias("item"))
    return count_of_classes(*set_classes(owned_sets(members))).select(F.col("own").alias("bucket"), "triangles")


def ss_restart(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A run stops after a part of the files; a second one goes on from its checkpoint when the rest has come."""
    rows = _events(spark, sf_dir)
    middle = rows.agg(F.expr("percentile_disc(0.5) within group (order by event_id)")).first()[0]
    folder, run = replay(rows.where(F.col("event_id") <= middle), 2), _folder(spark)
    counts = lambda: stream(spark, folder, None).groupBy("event_type").agg(F.count("*").alias("events"))
    drain(counts(), "update", ["event_type"], run)
    replay(rows.where(F.col("event_id") > middle), 1, folder)
    return drain(counts(), "update", ["event_type"], run)


def ss_append_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows that the watermark has closed, once each: all but those within the delay of the last event."""
    counts = stream(spark, replay(_events(spark, sf_dir), 3)).groupBy(F.window("ts", "60 minutes"), "event_type").agg(F.count("*").alias("events"))
    return drain(counts.select(_start(), "event_type", "events"), "append")


_HOUR = "cast(epoch(date_trunc('hour', ts)) as bigint)"
_ACTS = f"acts as (select {_HOUR} bucket, event_type, user_id, count(*) n from events group by all)"
SQL = {
    "ss_tumbling_coact": f"with {_ACTS} select x.user_id src, y.user_id dst, cast(1000000 // sum(x.n * y.n) as bigint) weight from acts x join acts y on x.bucket = y.bucket and x.event_type = y.event_type and x.user_id < y.user_id group by 1, 2",
    "ss_sliding_counts": "select cast(epoch_us(ts) // 900000000 - k as bigint) * 900 bucket, event_type, count(*) events from events, range(4) r(k) group by 1, 2",
    "ss_session_users": "with e as (select user_id, ts, epoch_us(ts) us, case when lag(ts) over w is null or ts >= lag(ts) over w + interval 30 minutes then 1 else 0 end fresh from events window w as (partition by user_id order by ts)), s as (select user_id, us, sum(fresh) over (partition by user_id order by ts) k from e) select user_id, min(us) began, count(*) events from s group by user_id, k",
    "ss_dedup_events": "select event_id, user_id from events",
    "ss_stream_static": "select c_nationkey, event_type, count(*) events from events join customer on user_id = c_custkey group by 1, 2",
    "ss_stream_stream": "select a.event_id click, b.event_id purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 10 minutes",
    "ss_state_degree": "select user_id, count(*) events, max(event_id) last_event from events group by user_id",
    "ss_window_triangles": f"with {_ACTS}, e as (select distinct x.bucket, x.user_id s, y.user_id d from acts x join acts y on x.bucket = y.bucket and x.event_type = y.event_type and x.user_id < y.user_id) select x.bucket, count(*) triangles from e x join e y on x.bucket = y.bucket and x.d = y.s join e z on z.bucket = x.bucket and z.s = x.s and z.d = y.d group by 1",
    "ss_restart": "select event_type, count(*) events from events group by 1",
    "ss_append_windows": f"select {_HOUR} bucket, event_type, count(*) events from events group by 1, 2 having {_HOUR} + 3600 <= (select epoch(max(ts)) - 600 from events)",
}


def queries() -> dict:
    return {f.__name__: f for f in (ss_tumbling_coact, ss_sliding_counts, ss_session_users, ss_late_dropped, ss_dedup_events, ss_stream_static, ss_stream_stream, ss_state_degree, ss_components, ss_window_triangles, ss_restart, ss_append_windows)}


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
