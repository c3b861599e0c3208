"""Streams over the events: windows, sessions, deduplication, interval joins, and monitors that say when a synopsis is stale."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from patcard.sources.workspace import workspace

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 4) -> DataFrame:
    """Parquet files as they arrive, with a stated schema and ten minutes' patience."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(folder).withWatermark("ts", "10 minutes")


def cut_into_files(spark: SparkSession, sf_dir: str, files: int = 8) -> str:
    """The events in files by time."""
    path = workspace(spark, "events")
    ev = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    ev.repartitionByRange(files, "ts").write.parquet(path)
    return path


def drain(spark: SparkSession, out: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, then read what it has written. Append goes to Parquet, other modes keep the last state of each batch."""
    path = workspace(spark, name)
    w = out.writeStream.option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        w.format("parquet").start(f"{path}/out").awaitTermination()
    else:
        w.foreachBatch(lambda df, _: df.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{path}/out")).start().awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{path}/out")


def new_edges_by_window(events: DataFrame, width: str = "6 hours", slide: str | None = None) -> DataFrame:
    """Events in each window and of each kind; the same expression serves streams and tables."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def dedupe(events: DataFrame) -> DataFrame:
    item = F.get_json_object("props", "$.k")
    return events.withColumn("item", item).dropDuplicatesWithinWatermark(["user_id", "item", "event_type"]).select("user_id", "item", "event_type")


def click_then_purchase(events: DataFrame) -> DataFrame:
    """A two-edge pattern in time: a click and a purchase of one user within an hour."""
    c = events.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t0"), F.col("event_id").alias("click"))
    p = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("purchase"))
    return c.join(p, F.expr("u = user_id and t1 between t0 and t0 + interval 1 hour")).select("user_id", "click", "purchase")


def drift(events: DataFrame, built_on: int, shares: tuple[float, ...] = (0.05, 0.1)) -> DataFrame:
    """(seen, share, rebuild, urgent) after each batch: how much has come since an index was built on built_on rows. Events are counted where they are read; only the counts of some parts meet in the state's single key."""

    def count(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = (state.get[0] if state.exists else 0) + sum(int(b["n"].sum()) for b in batches)
        state.update((seen,))
        share = seen / max(1, built_on)
        yield pd.DataFrame({"seen": [seen], "share": [share], "rebuild": [share >= shares[0]], "urgent": [share >= shares[-1]]})

    def partial(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        yield pd.DataFrame({"k": [0], "n": [sum(len(b) for b in batches)]})

    counts = events.select("event_id").mapInPandas(partial, "k int, n long")
    return counts.groupBy("k").applyInPandasWithState(count, "seen long, share double, rebuild boolean, urgent boolean", "seen long", "update", GroupStateTimeout.NoTimeout)


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, n): tumbling counts when the first six hours' events come once more after all others: they are past the watermark and change nothing."""
    path = workspace(spark, "late")
    ev = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    first = ev.agg(F.min("ts").alias("t0"))
    late = ev.crossJoin(F.broadcast(first)).where(F.col("ts") < F.col("t0") + F.expr("interval 6 hours")).drop("t0")
    counts = None
    for part in (ev, late, ev.orderBy(F.desc("ts")).limit(1)):  # a row at the end lets the watermark close the windows
        part.coalesce(1).write.mode("append").parquet(f"{path}/in")
        w = F.window("ts", "6 hours").alias("w")
        counts = spark.readStream.schema(SCHEMA).parquet(f"{path}/in").withWatermark("ts", "10 minutes").groupBy(w).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")
        counts.writeStream.format("parquet").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).outputMode("append").start(f"{path}/out").awaitTermination()
    return spark.read.schema(counts.schema).parquet(f"{path}/out")


def estimate_snapshots(spark: SparkSession, events: DataFrame, estimate, path: str) -> DataFrame:
    """foreachBatch: each batch's edges join those so far, kept as a table, and `estimate` of the snapshot is written with the batch's number; all estimates."""

    def one(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/events/batch={number}")  # a batch that is run again replaces itself
        so_far = spark.read.schema(SCHEMA).parquet(*[f"{path}/events/batch={k}" for k in range(number + 1)])
        estimate(so_far).withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{path}/estimates/at={number}")

    events.writeStream.foreachBatch(one).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/estimates").drop("at")


def snapshots(spark: SparkSession, sf_dir: str, calls: int = 10) -> DataFrame:
    """The walk for users who clicked and bought the same item, on every snapshot of the activity graph."""
    from patcard.operators.walk import vertex_walk
    from patcard.plans.query import parse_pattern
    from patcard.sources.graphs import PATTERNS, g_act

    q = parse_pattern(PATTERNS["P16"][1])
    events = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 4).parquet(cut_into_files(spark, sf_dir))
    return estimate_snapshots(spark, events, lambda ev: vertex_walk(g_act(spark, sf_dir, ev), q, calls=calls, order=("k", "u")), workspace(spark, "snapshots"))


def queries() -> dict:
    """name: (query, SQL of the batch twin or None)."""

    def stream(make, name, mode="append"):
        return lambda s, d: drain(s, make(read_events(s, cut_into_files(s, d))), name, mode)

    def rebuild(s, d):
        n = s.read.parquet(f"{d}/events.parquet").count()
        return drain(s, drift(read_events(s, cut_into_files(s, d)), n), "drift", "update")

    def kinds(s, d):
        static = s.createDataFrame([("click", 1), ("purchase", 2)], "event_type string, kind int")
        return drain(s, read_events(s, cut_into_files(s, d)).join(static, "event_type").select("event_id", "kind"), "static")

    def total(s, d):
        return drain(s, read_events(s, cut_into_files(s, d)).groupBy("event_type").agg(F.count("*").alias("n")), "complete", "complete")

    return {
        "stream_tumbling": (lambda s, d: drain(s, new_edges_by_window(read_events(s, cut_into_files(s, d))), "tumble", "complete"), "select time_bucket(interval 6 hours, ts, timestamp '1970-01-01') as start, event_type, count(*) n from events group by 1, 2"),
        "stream_sliding": (lambda s, d: drain(s, new_edges_by_window(read_events(s, cut_into_files(s, d)), "6 hours", "3 hours"), "slide", "complete"), "select start, event_type, count(*) n from (select time_bucket(interval 3 hours, ts, timestamp '1970-01-01') - interval (3 * k.range) hour as start, event_type from events, range(2) k) group by 1, 2"),
        "stream_sessions": (lambda s, d: drain(s, sessions(read_events(s, cut_into_files(s, d))), "sessions", "complete"), "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minute then 0 else 1 end as fresh from events), k as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) s from g) select user_id, min(ts) as start, count(*) n from k group by user_id, s"),
        "stream_dedupe": (stream(dedupe, "dedupe"), None),
        "stream_interval_join": (stream(click_then_purchase, "pairs"), "select a.user_id, a.event_id click, b.event_id purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts between a.ts and a.ts + interval 1 hour"),
        "stream_static_join": (kinds, "select event_id, case event_type when 'click' then 1 else 2 end kind from events where event_type in ('click', 'purchase')"),
        "stream_complete": (total, "select event_type, count(*) n from events group by 1"),
        "stream_drift": (rebuild, None),
        "stream_late": (late_rows, "select time_bucket(interval 6 hours, ts, timestamp '1970-01-01') as start, count(*) n from events group by 1 having time_bucket(interval 6 hours, max(ts), timestamp '1970-01-01') + interval 6 hour <= (select max(ts) from events) - interval 10 minute"),
        "stream_snapshots": (snapshots, None),
    }
