"""Registered queries run over whole tables, not over a fixed part of them."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from channelalign.functions import dtw, local_clusters
from channelalign.operators import embed
from channelalign.plans import register
from conftest import SF
from test_plans import plan


def test_conversations_of_all_ids_are_warped(spark, tmp_path):
    rows = [(conv, turn, "user") for conv in (1, 50, 900) for turn in range(conv % 7 + 1)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string").coalesce(1).write.parquet(f"{tmp_path}/conversations.parquet")
    found = register.queries()["dtw_small"](spark, str(tmp_path)).collect()
    assert sorted((r["i"], r["j"]) for r in found) == [(0, 1), (0, 2), (1, 2)]


def test_three_ways_map_exactly_up_to_most_series(spark, monkeypatch):
    asked = []

    def stop(vectors, p, tau, band=None, zero_tol=1e-9, landmarks=None, seed=0, exact_to=0):
        asked.append((landmarks, exact_to))
        raise InterruptedError

    monkeypatch.setattr(embed, "eigenmap", stop)
    with pytest.raises(InterruptedError):
        register.queries()["pipeline_three_ways"](spark, SF)
    assert asked == [(register.LANDMARKS, embed.MOST_SERIES)]


def test_histograms_of_all_weeks(spark):
    every = register.queries()["rayleigh_hist_segments"](spark, SF).collect()
    one = register.queries()["rayleigh_hist"](spark, SF).collect()
    assert {r["segment"] for r in every} == {0, 1, 2, 3, 4}
    assert sorted(tuple(r)[1:] for r in every if r["segment"] == 1) == sorted(map(tuple, one))


def test_mixtures_take_all_dimensions():
    points = np.random.default_rng(3).normal(size=(120, 64))
    drawn, weights = local_clusters.mixture(points, 10, 1, 30, diagonal=True)
    assert drawn.shape == (30, 64) and np.isfinite(drawn).all() and np.isfinite(weights).all()
    _, _, covs = local_clusters.fit_mixture(points, 4, diagonal=True)
    assert all((c == np.diag(np.diag(c))).all() for c in covs)


def test_series_are_warped_in_blocks_of_bounded_size(spark, tmp_path, monkeypatch):
    """More series than a task should hold, and turns beyond 32."""
    rows = [(conv, turn, "user") for conv in range(40) for turn in (range(conv % 7 + 1) if conv != 3 else range(30, 60))]
    spark.createDataFrame(rows, "conv_id long, turn long, role string").coalesce(1).write.parquet(f"{tmp_path}/conversations.parquet")
    series = register._conversation_series(spark, str(tmp_path))
    monkeypatch.setattr(embed, "BLOCK", 3)
    sizes = [r["count"] for r in embed._blocks_meet(series, 8).groupBy("p", "q").count().collect()]
    assert max(sizes) <= 6 and len(sizes) == 14 * 15 // 2
    dense = {r["i"]: np.bincount(r["bins"], r["cnts"], 61) for r in series.collect()}
    found = embed.distances(series).collect()
    assert len(found) == 40 * 39 // 2
    assert all(r["d"] == dtw.distance(dense[r["i"]], dense[r["j"]]) for r in found)


def test_laplacian_small_reads_the_events(spark):
    frame = register.queries()["laplacian_small"](spark, SF)
    assert any(f.endswith("events.parquet") for f in frame.inputFiles())
    rows = {(r["i"], r["j"]): r["l"] for r in frame.collect()}
    n = 1 + max(i for i, _ in rows)
    assert len(rows) == n * n and all(abs(sum(rows[i, j] for j in range(n))) < 1e-5 for i in range(n))


def test_rounding_is_that_of_decimals(spark):
    """Most numbers are rounded by arithmetic; ties, large numbers and what is no number still go by decimals."""
    rng = np.random.default_rng(1)
    numbers = [1 / 1024, 3 / 1024, -1 / 1024, 0.0000000005, 0.1234567885, 0.1234567895, -0.1, 1e-12, -1e-12, 2.5, 0.0, -0.0, 1e300, -123456789.123456789, 3e9 + 0.5, float("nan"), float("inf"), -float("inf"), None, *(k / 2048 for k in range(2048)), *map(float, rng.random(3000)), *map(float, rng.normal(size=500) * 1e6)]
    frame = spark.createDataFrame([(x,) for x in numbers], "x double")
    for digits in (4, 6, 9):
        got = register.rounded(frame, digits)
        both = frame.select(register._rounded("x", digits).alias("got"), F.round("x", digits).alias("want"))
        assert both.where("NOT (got <=> want)").count() == 0 and got.dtypes == frame.dtypes
        assert "FLOOR" in plan(got)


def test_equal_series_are_sent_once(spark, monkeypatch):
    """A block's equal series are one row for each other block, and rows of pairs come packed, few pairs at a time."""
    rows = [("user", conv, turn, 1) for conv in range(90) for turn in range(conv % 4 + 1)]
    series = embed.series(spark.createDataFrame(rows, "channel string, entity long, bin long, cnt long"), 32)
    monkeypatch.setattr(embed, "OWN", 3)
    monkeypatch.setattr(embed, "OTHERS", 5)
    monkeypatch.setattr(embed, "SLICE", 40)
    monkeypatch.setattr(embed, "ROWS", 7)
    met = embed._blocks_meet(series, 2)
    assert met.count() <= 2 * 2 * 4
    assert "posexplode" in plan(embed.distances(series, blocks=2))
    dense = {r["i"]: np.bincount(r["bins"], r["cnts"], 32) for r in series.collect()}
    found = {(r["i"], r["j"]): r["d"] for r in embed.distances(series, blocks=2).collect()}
    assert found == {(i, j): dtw.distance(dense[i], dense[j]) for i in dense for j in dense if i < j}
    lap = {(r["i"], r["j"]): r["l"] for r in embed.laplacian(embed.affinity(series, 5.0, blocks=2)).collect()}
    w = {(i, j): np.exp(-found[min(i, j), max(i, j)] / 5.0) for i in dense for j in dense if i != j}
    assert len(lap) == len(dense) ** 2 and all(abs(lap[k] + w[k]) < 1e-12 for k in w)
    assert all(abs(lap[i, i] - sum(w[i, j] for j in dense if j != i)) < 1e-9 for i in dense)
