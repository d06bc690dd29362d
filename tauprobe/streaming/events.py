"""Structured Streaming over events: windows, sessions, duplicates, state and late rows. Each runs whenever a part of its input has arrived, and ends."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tauprobe.session import scratch


def timed(rows: DataFrame) -> DataFrame:
    """Watermarks need points in time: wall-clock times are taken in the session's zone, and results are given back likewise."""
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


@dataclass
class Feed:
    """A folder in which files arrive: the parts that are still to come, in their order."""

    path: str
    parts: list[DataFrame]

    def arrive(self) -> None:
        if self.parts:
            self.parts.pop(0).write.mode("append").parquet(self.path)


def as_stream(spark: SparkSession, rows: DataFrame, parts: int = 4, order: str = "ts") -> tuple[DataFrame, Feed]:
    """The rows as a file stream that arrives in so many parts of their order, each of as many files as Spark writes; the first is there."""
    rows = timed(rows)
    place = F.col(order).cast("double")
    cuts = rows.agg(F.percentile_approx(place, [i / parts for i in range(1, parts)])).first()[0] or []
    number = sum((F.when(place > c, 1).otherwise(0) for c in cuts), F.lit(0))
    feed = Feed(scratch(spark, "stream"), [rows.where(number == i) for i in range(len(cuts) + 1)])
    feed.arrive()
    return spark.readStream.schema(rows.schema).parquet(feed.path), feed


def finish(spark: SparkSession, stream: DataFrame, mode: str, feeds: list[Feed], keys: list[str] | None = None) -> DataFrame:
    """Runs the stream once for each part that arrives, from its progress; of updated rows the last one counts, of complete results the last."""
    out = scratch(spark, "stream-out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/batch={number}")

    while True:
        stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{out}-progress").trigger(availableNow=True).start().awaitTermination()
        if not any(f.parts for f in feeds):
            break
        for f in feeds:
            f.arrive()
    found = spark.read.parquet(f"{out}/batch=*").drop("batch")
    if mode == "complete":
        return found.where(F.col("_batch") == found.agg(F.max("_batch")).first()[0]).drop("_batch")
    if keys is None:
        return found.drop("_batch")
    rest = [c for c in found.columns if c not in (*keys, "_batch")]
    last = found.groupBy(*keys).agg(F.max(F.struct("_batch", *rest)).alias("last"))
    return last.select(*keys, *[f"last.{c}" for c in rest])


def tumbling(spark: SparkSession, events: DataFrame) -> DataFrame:
    s, feed = as_stream(spark, events)
    counted = s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events"))
    return finish(spark, counted.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "events"), "update", [feed], ["start", "event_type"])


def sliding(spark: SparkSession, events: DataFrame) -> DataFrame:
    s, feed = as_stream(spark, events)
    counted = s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("events"))
    return finish(spark, counted.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "events"), "update", [feed], ["start"])


def sessions(spark: SparkSession, events: DataFrame) -> DataFrame:
    """Sessions that a pause of half an hour ends; those that part boundaries cut grow together again in the kept state."""
    s, feed = as_stream(spark, events)
    counted = s.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events"))
    return finish(spark, counted.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "events"), "complete", [feed])


def dedup(spark: SparkSession, events: DataFrame) -> DataFrame:
    s, feed = as_stream(spark, events)
    return finish(spark, s.select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]), "append", [feed]).agg(F.count(F.lit(1)).alias("kinds"))


def stateful(spark: SparkSession, events: DataFrame) -> DataFrame:
    """Running counts of each user in kept state."""

    def count(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(p) for p in parts)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n]})

    s, feed = as_stream(spark, events)
    counted = s.select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(count, "user_id bigint, events bigint", "n bigint", "update", GroupStateTimeout.NoTimeout)
    return finish(spark, counted, "update", [feed], ["user_id"])


def late(spark: SparkSession, events: DataFrame) -> DataFrame:
    """Hourly counts when files come in an order that makes some rows late: those behind the watermark do not count."""
    s, feed = as_stream(spark, events.withColumn("shuffled", F.pmod(F.xxhash64("event_id"), F.lit(4)) * 10_000_000 + F.col("event_id")), order="shuffled")
    counted = s.withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("events"))
    return finish(spark, counted.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "events"), "update", [feed], ["start"])


def interval_join(spark: SparkSession, events: DataFrame) -> DataFrame:
    """Two streams: each purchase with the same user's clicks of the hour before. Watermarks let go of what cannot meet any more."""

    feeds = []

    def side(kind: str, prefix: str) -> DataFrame:
        rows, feed = as_stream(spark, events.where(F.col("event_type") == kind).select("event_id", "user_id", "ts"))
        feeds.append(feed)
        return rows.select(F.col("event_id").alias(f"{prefix}_id"), F.col("user_id").alias(f"{prefix}_user"), F.col("ts").alias(f"{prefix}_ts")).withWatermark(f"{prefix}_ts", "1 hour")

    purchases, clicks = side("purchase", "purchase"), side("click", "click")
    met = purchases.join(clicks, F.expr("click_user = purchase_user and click_ts <= purchase_ts and click_ts >= purchase_ts - interval 1 hour"))
    return finish(spark, met.select("purchase_id", "click_id"), "append", feeds)


def static_join(spark: SparkSession, customers: DataFrame, nations: DataFrame) -> DataFrame:
    """A stream of customers against the table of nations."""
    s, feed = as_stream(spark, customers.select("c_custkey", "c_nationkey"), order="c_custkey")
    n = nations.select("n_nationkey", "n_name")
    joined = s.join(F.broadcast(n), s.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))
    return finish(spark, joined, "update", [feed], ["n_name"])
