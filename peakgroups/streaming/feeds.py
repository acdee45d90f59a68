"""Networks from event streams (S1-S7). The stream feeds snapshots; clustering is batch."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.operators.meeting import meeting_links
from peakgroups.plans.hierarchy import MutualPeakClusterer, middle_level
from peakgroups.plans.measures import f1_harmonic
from peakgroups.sources.networks import load_network

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events_with_time(events: DataFrame, late: str = "30 minutes") -> DataFrame:
    """Events with a watermark, each id once (S6). Rows without time or user are left out."""
    e = events.where("ts is not null and user_id is not null").withColumn("ts", F.col("ts").cast("timestamp"))
    if not e.isStreaming:
        return e.dropDuplicates(["event_id"])
    return e.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def window_activity(events: DataFrame, size: str = "10 minutes", slide: str | None = None, late: str = "30 minutes") -> DataFrame:
    """``start, user_id, n`` by tumbling (S1) or sliding (S2) windows; append mode works."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events_with_time(events, late).groupBy(w.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def session_activity(events: DataFrame, gap: str = "10 minutes", late: str = "30 minutes") -> DataFrame:
    """``start, stop, user_id, n`` by sessions of each user (S3)."""
    s = F.session_window("ts", gap)
    return events_with_time(events, late).groupBy(s.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n")


def activity_links(activity: DataFrame) -> DataFrame:
    """Links between users active in the same window, weight the number of windows."""
    return meeting_links(activity.selectExpr("start as slot", "user_id as user"))


def session_links(sessions: DataFrame, bucket_seconds: int = 600) -> DataFrame:
    """Links between users whose sessions overlap: buckets of time make an equi-join of the
    interval join, and a pair counts in the first bucket that both have."""
    s = sessions.select("user_id", F.unix_timestamp("start").alias("t0"), F.unix_timestamp("stop").alias("t1"))
    s = s.select(F.col("user_id").alias("user"), "t0", "t1", F.explode(F.expr(f"sequence(t0 div {bucket_seconds}, t1 div {bucket_seconds})")).alias("slot"))
    return meeting_links(s, times=True, where=f"t0 <= u1 and u0 <= t1 and slot = greatest(t0, u0) div {bucket_seconds}")


def handoffs(events: DataFrame) -> DataFrame:
    """``user_id, previous, event_id``: each event with the type its user did before (S7), by
    state kept per user; events of a batch are taken in order of time."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, batches, state):
        last = state.get[0] if state.exists else None
        for pdf in batches:
            pdf = pdf.sort_values(["ts", "event_id"])
            before = pd.Series([last, *pdf["event_type"].tolist()[:-1]], dtype="object")
            last = pdf["event_type"].iloc[-1]
            yield pd.DataFrame({"user_id": pdf["user_id"].to_numpy(), "previous": before.to_numpy(), "event_id": pdf["event_id"].to_numpy()})
        state.update((last,))

    e = events.select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type")
    return e.groupBy("user_id").applyInPandasWithState(step, "user_id long, previous string, event_id long", "last string", "append", GroupStateTimeout.NoTimeout)


class SnapshotClusterer:
    """``foreachBatch`` sink (S4, S5): adds a batch of activity to the snapshot's links,
    clusters it, and reports the F1h of the middle cover against the batch before."""

    def __init__(self, path: str, alarm: Callable[[int, float], None] | None = None, tolerance: float = 0.5):
        self.path, self.alarm, self.tolerance = path, alarm, tolerance
        self.drift: list[tuple[int, float]] = []
        self._cover = None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        # A batch that is run again writes its own folder again, so nothing counts twice.
        batch.write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")
        activity = spark.read.parquet(self.path).where(F.col("batch") <= batch_id)
        if not activity.limit(1).count():
            return
        h = MutualPeakClusterer().fit(load_network(activity_links(activity)))
        if not h.levels:
            return
        cover = h.flatten(middle_level(h.levels)).select("cluster", "node")
        if self._cover is not None:
            score = f1_harmonic(cover, self._cover)
            self.drift.append((batch_id, score))
            if self.alarm and score < self.tolerance:
                self.alarm(batch_id, score)
        self._cover = cover


def membership_asof(events: DataFrame, snapshots: DataFrame) -> DataFrame:
    """``event_id, cluster``: each event with the last membership ``(user_id, at, cluster)``
    not later than it, an as-of join by a union and one running window."""
    from pyspark.sql.window import Window

    e = events.select("user_id", F.col("ts").cast("timestamp").alias("t"), "event_id", F.lit(None).cast("long").alias("cluster"))
    s = snapshots.select("user_id", F.col("at").cast("timestamp").alias("t"), F.lit(None).cast("long").alias("event_id"), F.col("cluster").cast("long"))
    w = Window.partitionBy("user_id").orderBy("t", F.col("event_id").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    return e.union(s).withColumn("cluster", F.last("cluster", ignorenulls=True).over(w)).where("event_id is not null").select("event_id", "cluster")
