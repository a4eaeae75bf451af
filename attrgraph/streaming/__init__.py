"""Maintaining graphs from event streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.sources import bucket_of


def timed_events(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Events with a zoned ``ts`` and a watermark (works on batches too, where the watermark has no effect)."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def window_activity(events: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(start, user_id, n, value): tumbling, or sliding with ``slide``, activity of users."""
    frame = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy(frame.alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("value")).select(F.col("w.start").alias("start"), "user_id", "n", "value")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, end, n): a user's runs of events less than ``gap`` apart."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def window_edges(events: DataFrame, length: str = "10 minutes") -> DataFrame:
    """(start, a, b): users active in one window. Each window's users are gathered once and paired by expression."""
    users = events.groupBy(F.window("ts", length).alias("w")).agg(F.sort_array(F.collect_set("user_id")).alias("u"))
    first = users.select("w", F.posexplode("u").alias("i", "a"), "u")
    return first.select(F.col("w.start").alias("start"), "a", F.explode(F.slice("u", F.col("i") + 2, F.greatest(F.size("u") - F.col("i") - 1, F.lit(0)))).alias("b"))


def click_then_purchase(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, click_id, purchase_id): purchases of the same user at most ``within`` after a click; both watermarked."""
    left = clicks.select(F.col("user_id"), F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts"))
    right = purchases.select(F.col("user_id").alias("buyer"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("purchase_ts"))
    return left.join(right, F.expr(f"user_id = buyer and purchase_ts >= click_ts and purchase_ts <= click_ts + interval {within}")).select("user_id", "click_id", "purchase_id")


def label_before(events: DataFrame, labels: DataFrame) -> DataFrame:
    """As-of join: (event_id, user_id, label) with the user's latest label at or before the event.

    One sort by user and time over both tables; no range join.
    """
    both = labels.select("user_id", F.col("ts"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), "label").union(events.select("user_id", "ts", F.lit(1), "event_id", F.lit(None).cast(labels.schema["label"].dataType)))
    w = Window.partitionBy("user_id").orderBy("ts", "kind", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("label", F.last("label", ignorenulls=True).over(w)).where("kind = 1").select("event_id", "user_id", "label")


def merge_snapshot(path: str, buckets: int = 16) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink for edges (a, b): appends what a batch adds to a bucketed edge set, once.

    Each batch writes its own folder, which a retried batch overwrites; only buckets that the batch touches are read.
    """

    def sink(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        rows = batch.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a != b").distinct().withColumn("bucket", bucket_of("a", buckets))
        touched = [r.bucket for r in rows.select("bucket").distinct().collect()]
        try:
            known = spark.read.schema("a long, b long, bucket int, batch long").parquet(path).where(F.col("bucket").isin(touched) & (F.col("batch") != number))
            rows = rows.join(known.select("a", "b"), ["a", "b"], "left_anti")
        except Exception as e:  # nothing written yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
        rows.select("a", "b", "bucket").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/batch={number}")

    return sink


def read_snapshot(spark, path: str) -> DataFrame:
    return spark.read.schema("a long, b long, bucket int, batch long").parquet(path).select("a", "b").distinct()


def affected_seeds(supports: DataFrame, changed: DataFrame) -> DataFrame:
    """(seed_id): watched seeds whose support (seed_id, node_id) holds an end of a changed edge (a, b); these are run again."""
    ends = changed.select(F.explode(F.array("a", "b")).alias("node_id")).distinct()
    return supports.join(ends, "node_id", "left_semi").select("seed_id").distinct()


def histogram_state(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Running count of each event type of a user, for ``applyInPandasWithState`` (state: one map as parallel arrays)."""
    counts = dict(zip(*state.get, strict=True)) if state.exists else {}
    for pdf in frames:
        for kind, n in pdf["event_type"].value_counts().items():
            counts[kind] = counts.get(kind, 0) + int(n)
    names = sorted(counts)
    state.update((names, [counts[k] for k in names]))
    yield pd.DataFrame({"user_id": [key[0]] * len(names), "attr": names, "value": [float(counts[k]) for k in names]})


def running_histograms(events: DataFrame) -> DataFrame:
    """(user_id, attr, value) of users seen in each micro-batch: their event types so far."""
    return events.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(histogram_state, "user_id long, attr string, value double", "names array<string>, counts array<long>", "update", "NoTimeout")
