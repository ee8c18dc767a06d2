"""Structured Streaming forms: bins, first events, segments, late data."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from channelalign.operators import segments
from channelalign.operators.binning import bin_events
from channelalign.sources.state import SegmentStore


def _timed(events: DataFrame, delay: str) -> DataFrame:
    return events.withColumn("ts", F.timestamp_micros("us")).withWatermark("ts", delay)


def bin_stream(events: DataFrame, width_us: int, origin_us: int = 0, delay: str = "1 hour") -> DataFrame:
    """channel, entity, bin, cnt as a stream: tumbling windows with the pinned origin; events behind the watermark are dropped and counted by Spark."""
    offset = F.window("ts", f"{width_us} microseconds", startTime=f"{origin_us % width_us} microseconds")
    counts = _timed(events, delay).groupBy("channel", F.col("src").alias("entity"), offset.alias("w")).count()
    start = F.unix_micros("w.start") - F.lit(origin_us)
    return counts.select("channel", "entity", ((start - F.pmod(start, F.lit(width_us))) / width_us).cast("long").alias("bin"), F.col("count").alias("cnt"))


def sliding_activity(events: DataFrame, size: str, slide: str, delay: str = "1 hour") -> DataFrame:
    """Counts per channel in overlapping windows, for watching only: scores of overlapping segments must not be added."""
    return _timed(events, delay).groupBy("channel", F.window("ts", size, slide).alias("w")).count().select("channel", F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.col("count").alias("n"))


def bursts(events: DataFrame, gap: str, delay: str = "1 hour") -> DataFrame:
    """Sessions of an entity: its events with no pause of ``gap``."""
    return _timed(events, delay).groupBy("channel", F.col("src").alias("entity"), F.session_window("ts", gap).alias("w")).count().select("channel", "entity", F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.col("count").alias("n"))


def without_repeats(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events with the same channel and key within the delay once."""
    return _timed(events, delay).dropDuplicatesWithinWatermark(["channel", "key"]).drop("ts")


def first_events(events: DataFrame, idle: str | None = None, delay: str = "1 hour") -> DataFrame:
    """channel, entity, first_us, n as a stream of updates: each entity's first event and count so far, in state.

    idle: an entity without an event for that long behind the watermark is forgotten, which bounds the state; its
    next event counts as its first. Without it the state grows with the number of entities.
    """
    schema = "channel string, entity long, first_us long, n long"
    idle_ms = None if idle is None else int(pd.Timedelta(idle).total_seconds() * 1000)

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        first, n = state.get if state.exists else (None, 0)
        last = 0
        for rows in batches:
            low, last = int(rows["us"].min()), max(last, int(rows["us"].max()))
            first, n = low if first is None else min(first, low), n + len(rows)
        state.update((first, n))
        if idle_ms is not None:
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), last // 1000) + idle_ms)
        yield pd.DataFrame({"channel": [key[0]], "entity": [key[1]], "first_us": [first], "n": [n]})

    rows = events if idle is None else _timed(events, delay)
    rows = rows.select("channel", F.col("src").alias("entity"), "us", *([] if idle is None else ["ts"]))
    timeout = GroupStateTimeout.NoTimeout if idle is None else GroupStateTimeout.EventTimeTimeout
    return rows.groupBy("channel", "entity").applyInPandasWithState(update, schema, "first_us long, n long", "update", timeout)


def co_occurrences(left: DataFrame, right: DataFrame, delta_us: int, delay: str = "1 hour") -> DataFrame:
    """u, v, us of events of two streams at most delta_us apart. Streams must meet on an equality: bins of that width, each left event in its own and both neighbours. Both sides' state is bounded by watermark and distance."""
    at, gap = F.floor(F.col("us") / delta_us), f"INTERVAL '{delta_us / 1_000_000:.6f}' SECOND"
    a = _timed(left, delay).select(F.col("src").alias("u"), F.col("ts").alias("ta"), "us", F.explode(F.array(at - 1, at, at + 1)).alias("bin_a"))
    b = _timed(right, delay).select(F.col("src").alias("v"), F.col("ts").alias("tb"), at.alias("bin_b"))
    return a.join(b, F.expr(f"bin_a = bin_b AND tb >= ta - {gap} AND tb <= ta + {gap}")).select("u", "v", "us")


def segment_handler(store: SegmentStore, left: str, right: str, width_us: int, every_days: int, compact_every: int = 16, **how) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: adds a micro-batch's bins to their segments and scores these segments anew from all their bins.

    A segment may come in any number of batches, in any order and late: its new scores take the place of the old
    ones (see SegmentStore), and events that came after its first scores are counted in store.late(). A batch that
    comes again finds its segments done.
    """

    def handle(batch: DataFrame, batch_id: int) -> None:
        binned = segments.plan(bin_events(batch, width_us, 0), segments.segment_of_bin(width_us, every_days))
        touched = store.add_bins(batch_id, binned)
        todo = [s for s in touched if not store.has(s, batch_id)]
        if late := [s for s in todo if store.has(s)]:
            store.note_late(batch_id, late)
        for segment in todo:
            rescore(store, segment, left, right, batch_id, **how)
        if compact_every and batch_id % compact_every == compact_every - 1:
            store.compact()

    return handle


def start(events: DataFrame, store: SegmentStore, left: str, right: str, width_us: int, every_days: int, checkpoint: str, trigger: str | None = None, **how) -> StreamingQuery:
    """Runs what the stream has, then stops; with ``trigger`` ("10 minutes") it runs on, a micro-batch in that time."""
    writer = events.writeStream.foreachBatch(segment_handler(store, left, right, width_us, every_days, **how)).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if trigger is None else writer.trigger(processingTime=trigger)).start()


def rescore(store: SegmentStore, segment: int, left: str, right: str, batch: int, **how) -> None:
    """Scores a segment from all bins that the store has of it; the state then holds these scores instead of earlier ones."""
    store.commit(segment, segments.score_segments(store.bins([segment]), left, right, **how), batch)


def incremental_bins(events: DataFrame, width_us: int, path: str, checkpoint: str, origin_us: int = 0) -> None:
    """Bins of a stream without state: each micro-batch's counts are written under its number (again if it comes again); read_incremental_bins() adds them up."""

    def handle(batch: DataFrame, batch_id: int) -> None:
        bin_events(batch, width_us, origin_us).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    events.writeStream.foreachBatch(handle).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def read_incremental_bins(spark, path: str) -> DataFrame:
    rows = spark.read.schema("channel string, entity long, bin long, cnt long, batch long").parquet(path)
    return rows.groupBy("channel", "entity", "bin").agg(F.sum("cnt").alias("cnt"))
