"""Streams over day files."""

from pyspark.sql import functions as F

from channelalign.functions import sqlfuncs
from channelalign.operators import binning, segments
from channelalign.sources.channels import EVENT_SCHEMA, event_stream
from channelalign.sources.planted import planted_events
from channelalign.sources.state import SegmentStore, StateStore, read_days, write_days
from channelalign.streaming import streams
from conftest import SF


def finished(frame, name: str, mode: str, spark, path: str):
    frame.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{path}/{name}").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def test_day_files_and_windows(spark, tmp_path):
    events, _ = planted_events(spark, SF, 31)
    write_days(events, f"{tmp_path}/days")
    assert read_days(spark, f"{tmp_path}/days").count() == events.count()
    assert read_days(spark, f"{tmp_path}/days", "2024-01-05", "2024-01-06").select("day").distinct().count() == 1
    stream = event_stream(spark, f"{tmp_path}/days", 40)
    got = finished(streams.bin_stream(stream, binning.HOUR_US, 0), "bins", "complete", spark, str(tmp_path))
    want = binning.bin_events(events, binning.HOUR_US, 0)
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()
    first = finished(streams.first_events(stream), "firsts", "update", spark, str(tmp_path))
    assert first.groupBy().sum("n").first()[0] == events.count()
    assert finished(streams.sliding_activity(stream, "2 days", "1 day"), "slides", "complete", spark, str(tmp_path)).count() > 60
    assert finished(streams.bursts(stream, "1 hour"), "bursts", "append", spark, str(tmp_path)).count() > 100


def test_repeats_and_co_occurrence(spark, tmp_path):
    rows = [("a", 1, None, 10_000_000, 1), ("a", 1, None, 10_000_000, 1), ("b", 2, None, 12_000_000, 2), ("b", 3, None, 90_000_000, 3)]
    spark.createDataFrame(rows, EVENT_SCHEMA).coalesce(1).write.parquet(f"{tmp_path}/e")
    stream = event_stream(spark, f"{tmp_path}/e")
    assert finished(streams.without_repeats(stream), "once", "append", spark, str(tmp_path)).count() == 3
    near = streams.co_occurrences(stream.where("channel = 'a'"), event_stream(spark, f"{tmp_path}/e").where("channel = 'b'"), 5_000_000)
    assert {(r["u"], r["v"]) for r in finished(near, "near", "append", spark, str(tmp_path)).collect()} == {(1, 2)}


def test_state_store_replays(spark, tmp_path):
    store = StateStore(spark, f"{tmp_path}/state")
    state = spark.createDataFrame([(1, 2, 0.5, 1, 7)], "u long, v long, score double, n_segments long, last_segment long")
    store.commit(7, state)
    store.commit(7, state.union(state))  # comes again: nothing changes
    store.commit(3, store.read().unionByName(state))
    assert store.segments() == [7, 3] and store.read().count() == 2 and store.has(3) and not store.has(4)


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    row = spark.sql("SELECT time_bin(-1, 0, 10) AS b, rayleigh_cdf(0D, 1D) AS c, dtw(array(0, 5, 0), array(0, 0, 5)) AS d").first()
    assert (row["b"], row["c"], row["d"]) == (-1, 0.0, 5.0)
    assert [r["cnt"] for r in spark.sql("SELECT * FROM dense_series(array(1L, 3L), array(4L, 5L), 4)").collect()] == [0, 4, 0, 5]
    assert spark.sql("SELECT fit_rayleigh_agg(s) AS f FROM VALUES (3D), (4D) AS t(s)").first()["f"] == 2.5


def test_segment_store_revises_and_compacts(spark, tmp_path):
    store = SegmentStore(spark, f"{tmp_path}/segments")
    made = lambda *rows: spark.createDataFrame(list(rows), "u long, v long, score double")
    state = lambda: {(r["u"], r["v"]): (r["score"], r["n_segments"]) for r in store.read().collect()}
    assert state() == {}
    store.commit(0, made((1, 2, 1.0), (1, 3, 2.0)), 0)
    store.commit(1, made((1, 2, 4.0)), 1)
    store.commit(1, made((9, 9, 9.0)), 1)  # comes again: nothing changes
    assert state() == {(1, 2): (5.0, 2), (1, 3): (2.0, 1)}
    store.compact(keep=1)
    store.commit(0, made((1, 2, 0.5)), 2)  # revised after the snapshot: the old scores are taken back
    assert state() == {(1, 2): (4.5, 2)} and store.scores(0).count() == 1
    store.compact(keep=1)
    assert state() == {(1, 2): (4.5, 2)} and store.segments() == [0, 1] and store.has(0, 2) and not store.has(1, 2)


def test_a_week_in_two_batches_equals_the_whole(spark, tmp_path):
    events, _ = planted_events(spark, SF, 31)
    week = events.withColumn("us", F.col("us") - 1_704_067_200_000_000).where(F.col("us").between(0, 7 * binning.DAY_US - 1)).cache()
    week.where("key % 2 = 0").coalesce(1).write.parquet(f"{tmp_path}/files")
    week.where("key % 2 = 1").coalesce(1).write.mode("append").parquet(f"{tmp_path}/files")
    store = SegmentStore(spark, f"{tmp_path}/store")
    streams.start(event_stream(spark, f"{tmp_path}/files"), store, "a", "b", binning.HOUR_US, 7, f"{tmp_path}/checkpoint").awaitTermination()
    whole = segments.accumulate(segments.score_segments(segments.plan(binning.bin_events(week, binning.HOUR_US, 0), F.lit(0).cast("long")), "a", "b"))
    assert same_state(store.read()) == same_state(whole) != []
    late = store.late().collect()
    assert len(late) == 1 and late[0]["n_late"] in {week.where(f"key % 2 = {k}").count() for k in (0, 1)}
    streams.rescore(store, 0, "a", "b", 9)  # the same bins: the same state
    assert same_state(store.read()) == same_state(whole)


def same_state(frame):
    return sorted((r["u"], r["v"], round(r["score"], 9), r["n_segments"]) for r in frame.collect())
