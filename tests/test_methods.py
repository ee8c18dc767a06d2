"""Worked examples, invariants and edge frames."""

import math
from dataclasses import replace

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from channelalign.functions import dtw, local_clusters
from channelalign.operators import baselines, binning, cluster, embed, likelihood, matching, metrics, reduced, segments, similarity
from channelalign.operators.cluster import ClusterSpec
from channelalign.plans.pipeline import AlignSpec, MatchSpec, PlanTooLarge, align
from channelalign.sources.channels import EVENT_SCHEMA, split_usable
from channelalign.sources.planted import planted_events
from conftest import SF

BINNED = "channel string, entity long, bin long, cnt long"


@pytest.fixture(scope="module")
def example(spark):
    rows = [("a", 1, 0, 2), ("a", 1, 5, 1), ("a", 2, 1, 1), ("b", 11, 0, 2), ("b", 11, 5, 1), ("b", 12, 1, 2), ("b", 12, 5, 1)]
    return spark.createDataFrame(rows, BINNED)


def pairs_of(frame):
    return sorted((r["u"], r["v"]) for r in frame.select("u", "v").distinct().collect())


def test_worked_example(example):
    pairs = similarity.pairwise_cosine(example, "a", "b")
    got = {(r["u"], r["v"]): round(r["sim"], 6) for r in pairs.collect()}
    assert got == {(1, 11): 1.0, (1, 12): 0.2, (2, 12): 0.894427}
    assert pairs_of(matching.reconcile(pairs)) == [(1, 11), (2, 12)]
    assert len(pairs_of(matching.reconcile(pairs, rule="threshold", theta=0.1))) == 3


def test_physical_forms_agree(spark):
    events, _ = planted_events(spark, SF, 31)
    binned = binning.bin_events(events, binning.HOUR_US)
    key = lambda f: sorted((r["u"], r["v"], r["dot"], round(r["sim"], 12)) for r in f.collect())
    plain = key(similarity.pairwise_cosine(binned, "a", "b"))
    assert key(similarity.pairwise_cosine(binned, "a", "b", salts=3, hot=5)) == plain
    assert key(similarity.block_cosine(binning.to_vectors(binned), "a", "b", 3, 2)) == plain
    n = binning.span(events, binning.HOUR_US).first()["n_bins"]
    assert key(baselines.dense_cosine(binning.to_vectors(binned), "a", "b", n)) == plain
    assert key(similarity.pairwise_cosine(binned, "a", "b", min_sim=0.2, prune=True)) == [p for p in plain if p[3] >= 0.2]
    one = binned.select("channel", "entity", F.lit(0).alias("cluster")).distinct()
    assert key(similarity.pairwise_cosine(binned, "a", "b", one)) == plain
    assert all(0 <= p[3] <= 1 + 1e-12 for p in plain)


def test_bins_add_up(spark):
    events, _ = planted_events(spark, SF, 31)
    fine, coarse = binning.bin_events(events, 3_600_000_000), binning.bin_events(events, 7_200_000_000)
    assert fine.agg(F.sum("cnt")).first()[0] == events.count()
    assert binning.rebin(fine, 2).exceptAll(coarse).count() == 0
    back = binning.from_vectors(binning.to_vectors(fine))
    assert back.exceptAll(fine).count() == 0


def test_bins_before_the_origin_are_negative(spark):
    events = spark.createDataFrame([("a", 1, None, -1, 0), ("a", 1, None, 0, 1), ("a", None, None, 5, 2), ("a", 1, None, None, 3)], EVENT_SCHEMA)
    assert sorted(r["bin"] for r in binning.bin_events(events, 10, 0).collect()) == [-1, 0]
    good, bad = split_usable(events)
    assert (good.count(), bad.count()) == (2, 2)


def test_reduced_features_are_scaled(spark):
    events, _ = planted_events(spark, SF, 31, profile=True)
    f = np.array([r["f"] for r in reduced.reduced_features(events, binning.HOUR_US).collect()])
    assert f.shape[1] == 3 and np.allclose(f.max(axis=0), 1) and (f >= 0).all()


def test_warping_distance():
    assert dtw.distance([0, 5, 0], [0, 0, 5]) == 5
    assert dtw.distance([1, 1, 2], [1, 2]) == 0
    assert dtw.distance([5], [0, 0, 0]) == 15


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sampled_from([0, 0, 0, 1, 2, 5]), min_size=1, max_size=25), st.lists(st.sampled_from([0, 0, 0, 1, 3]), min_size=1, max_size=25))
def test_warping_of_runs_is_exact(x, y):
    runs = [dtw.compress(np.flatnonzero(z), np.array(z)[np.flatnonzero(z)], len(z)) for z in (x, y)]
    assert dtw.run_distance(*runs) == dtw.distance(x, y) == dtw.distance(y, x) == dtw.distance(x, y, band=50)
    assert dtw.distance(x, x) == 0


def test_laplacian_of_a_path_and_its_map(spark):
    w = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0)], "i long, j long, w double")
    lap = np.zeros((3, 3))
    for r in embed.laplacian(w).collect():
        lap[r["i"], r["j"]] = r["l"]
    assert np.allclose(np.linalg.eigvalsh(lap), [0, 1, 3]) and np.allclose(lap.sum(axis=1), 0)
    values = embed._eigen(np.diag(np.diag(lap)) - lap, 2, 1e-9)
    assert np.allclose(values[1], [1, 3]) and np.allclose(values[0].sum(axis=0), 0)


def test_eigenmap_and_landmarks(spark):
    rows = [(c, e, b, 1 + (e % 2)) for c in "ab" for e in range(6) for b in (range(0, 12, 3) if e % 2 else range(10, 22, 2))]
    v = embed.series(spark.createDataFrame(rows, BINNED), 24)
    exact = {(r["channel"], r["entity"]): np.array(r["f"]) for r in embed.eigenmap(v, 2, 5.0).collect()}
    assert len(exact) == 12 and all(len(f) == 2 for f in exact.values())
    first = {e: {round(float(exact[c, e][0]), 6) for c in "ab"} for e in range(6)}  # parts the two kinds of series
    assert all(len(x) == 1 for x in first.values()) and first[0] == first[2] == first[4] != first[1] == first[3] == first[5]
    assert embed.eigenmap(v, 2, 5.0, landmarks=6).count() == 12


def test_local_clusters():
    rng = np.random.default_rng(3)
    points = np.concatenate([rng.normal(c, 0.05, (60, 2)) for c in ((0, 0), (3, 0), (0, 3))])
    centres, sizes = local_clusters.kmeans(points, 3, 1)
    assert sorted(sizes) == [60, 60, 60]
    share, means, _ = local_clusters.fit_mixture(points, 3, 1)
    assert np.allclose(sorted(share), 1 / 3, atol=0.05) and np.allclose(sorted(means.sum(axis=1)), [0, 3, 3], atol=0.1)
    drawn, weights = local_clusters.mixture(points, 3, 1, 30)
    assert drawn.shape == (30, 2) and (weights > 0).all()
    assert len(local_clusters.kmeans(points[:2], 5)[0]) == 2
    assert len(local_clusters.kmeans(np.ones((9, 2)), 3)[0]) == 1


def test_representative_clusters(spark):
    rng = np.random.default_rng(5)
    rows = [(c, i, list(map(float, rng.normal((i % 3) * 4, 0.1, 2)))) for c in ("a", "b") for i in range(90)]
    f = spark.createDataFrame(rows, "channel string, entity long, f array<double>")
    for spec in (ClusterSpec(k=3, w=3), ClusterSpec(k=3, w=3, method="gmm"), ClusterSpec(k=3, w=2, representative="moments"), ClusterSpec(k=3, w=3, rounds=2), ClusterSpec(k=3, w=3, joint=False), ClusterSpec(k=3, w=30, subsets="literal")):
        labels, _ = cluster.representative_clusters(f, spec)
        groups = {r["entity"] % 3: r["cluster"] for r in labels.collect()}
        assert sorted(groups.values()) == [0, 1, 2], spec
        assert labels.select("entity", "cluster").distinct().count() == 90
    spread = sorted(map(tuple, cluster.representative_clusters(f.repartition(7), ClusterSpec(k=3, w=3))[0].collect()))
    assert spread == sorted(map(tuple, cluster.representative_clusters(f.coalesce(1), ClusterSpec(k=3, w=3))[0].collect()))
    wide = cluster.label(f, np.concatenate([np.eye(2)[:1] * i for i in range(2100)]))
    assert wide.count() == 180
    assert cluster.label(f, [[0.0, 0.0], [4.0, 4.0], [8.0, 8.0]], nearest=2).count() == 360


def test_rayleigh(spark):
    fit = likelihood.fit_rayleigh(spark.createDataFrame([(3.0,), (4.0,)], "s double")).first()
    assert fit["sigma"] == 2.5 and fit["n"] == 2
    sample = np.random.default_rng(1).rayleigh(0.3, 4000)
    drawn = spark.createDataFrame([(float(x),) for x in sample], "s double")
    assert abs(likelihood.fit_rayleigh(drawn).first()["sigma"] - 0.3) < 0.01
    assert likelihood.ks_rayleigh(drawn).first()["ks"] < 0.03
    both = spark.createDataFrame([(0.5, 0.2), (0.4, 0.4), (0.2, 0.5)], "x double, y double").select(likelihood.overlap(F.col("x"), F.col("y")).alias("o"), "x", "y").collect()
    grid = np.linspace(0, 5, 200_001)
    for r in both:
        p, q = (grid / s**2 * np.exp(-(grid**2) / (2 * s * s)) for s in (r["x"], r["y"]))
        assert abs(r["o"] - np.minimum(p, q).sum() * (grid[1] - grid[0])) < 1e-4
    rising = spark.range(5).select((F.col("id") / 5).alias("sim"), F.lit(0).alias("u"), F.lit(0).alias("v"))
    model = spark.createDataFrame([(0.5, 0.2)], "sigma1 double, sigma0 double")
    scores = [r["score"] for r in likelihood.score(rising, model).orderBy("sim").collect()]
    assert scores == sorted(scores) and math.isfinite(scores[0])


def test_training_sample_keeps_whole_entities(spark):
    events, _ = planted_events(spark, SF, 31)
    binned = binning.bin_events(events, binning.HOUR_US)
    some = likelihood.training_sample(binned, "a", "b", 0.5)
    kept = some.where("channel = 'a'").select("entity").distinct()
    assert 0 < kept.count() < 13
    assert some.where("channel = 'b'").count() == binned.where("channel = 'b'").count()
    assert binned.where("channel = 'a'").join(kept, "entity").count() == some.where("channel = 'a'").count()


def test_numbering_is_dense(spark):
    ids = spark.range(0, 500, 3).withColumnRenamed("id", "v")
    assert sorted(r["place"] for r in likelihood.numbered(ids, "v").collect()) == list(range(167))


def test_metrics_by_hand(spark):
    truth = spark.createDataFrame([(1, 1), (2, 2), (3, 3), (3, 4)], "u long, v long")
    found = spark.createDataFrame([(1, 1), (2, 9), (3, 3)], "u long, v long")
    assert metrics.matched_accuracy(found, truth).first()["ma"] == pytest.approx(2 / 3)
    share = lambda side, unit: metrics.not_matched(found, truth, side, unit).first()["accuracy"]
    assert share("forward", "entity") == pytest.approx(2 / 3)
    assert share("backward", "entity") == share("forward", "pair") == pytest.approx(0.5)
    row = metrics.summary(found, truth).first()
    assert (row["n_found"], row["n_right"], row["n_true"]) == (3, 2, 4) and row["jaccard"] == pytest.approx(2 / 5)
    assert metrics.matched_accuracy(found.limit(0), truth).first()["ma"] is None
    assert metrics.correct_count(found, truth).first()["n_entities"] == 2


def test_state_adds_retracts_and_nests(spark):
    one = spark.createDataFrame([(0, 1, 1, 2.0), (0, 1, 2, 1.0)], "segment long, u long, v long, score double")
    two = spark.createDataFrame([(1, 1, 1, 3.0), (1, 2, 2, 0.5)], "segment long, u long, v long, score double")
    state = segments.accumulate(two, segments.accumulate(one))
    assert {(r["u"], r["v"]): (r["score"], r["n_segments"], r["last_segment"]) for r in state.collect()} == {(1, 1): (5.0, 2, 1), (1, 2): (1.0, 1, 0), (2, 2): (0.5, 1, 1)}
    assert {(r["u"], r["v"]): r["score"] for r in segments.retract(state, two).collect()} == {(1, 1): 2.0, (1, 2): 1.0}
    assert segments.accumulate(two, segments.accumulate(one), keep_top=1).count() == 2
    assert segments.accumulate(one, keep_floor=1.5).count() == 1


def test_pipeline_switches(spark):
    events, truth = planted_events(spark, SF, 31)
    plain = pairs_of(align(events, "a", "b").matches)
    assert len(plain) == 11
    one = align(events, "a", "b", AlignSpec(feature="reduced", cluster=ClusterSpec(k=1)))
    assert pairs_of(one.matches) == plain
    assert set(pairs_of(align(events, "a", "b", AlignSpec(feature="reduced")).pairs)) <= set(pairs_of(align(events, "a", "b").pairs))
    with pytest.raises(PlanTooLarge):
        align(events, "a", "b", AlignSpec(most_products=10))


def test_edge_frames(spark):
    none = spark.createDataFrame([], EVENT_SCHEMA)
    assert align(none, "a", "b").matches.count() == 0
    assert binning.span(none, 10).first()["n_bins"] == 0
    lone = spark.createDataFrame([("a", 1, None, 5, 1)], EVENT_SCHEMA)
    assert align(lone, "a", "b").matches.count() == 0
    assert reduced.reduced_features(lone, 10).first()["f"] == [1.0, 0.0, 0.0]
    assert binning.sparsity(binning.bin_events(lone, 10), binning.span(lone, 10)).first()["fill"] == 1.0


def test_near_counts_cross_bin_edges(spark):
    events = spark.createDataFrame([("a", 1, None, 99, 1), ("b", 2, None, 101, 2), ("b", 3, None, 250, 3)], EVENT_SCHEMA)
    assert [(r["u"], r["v"], r["n"]) for r in similarity.near_counts(events, "a", "b", 100).collect()] == [(1, 2, 1)]


def test_subsets_grow_with_the_points(monkeypatch):
    spec = ClusterSpec(w=4)
    assert cluster.subset_count(spec, 1000) == 4
    monkeypatch.setattr(cluster, "SUBSET_POINTS", 100)
    assert cluster.subset_count(spec, 1000) == 10


def test_too_many_representatives_are_refused(spark):
    reps = spark.createDataFrame([(0, "a", i, [float(i), 1.0], 1.0) for i in range(10)], cluster.REPRESENTATIVE)
    assert cluster.global_centroids(reps, ClusterSpec(k=2), most=20).shape == (2, 2)
    with pytest.raises(ValueError, match="larger subsets"):
        cluster.global_centroids(reps, ClusterSpec(k=2), most=19)


def test_manhattan_labels(spark):
    f = spark.createDataFrame([("a", 1, [0.0, 3.0]), ("a", 2, [2.2, 2.2])], "channel string, entity long, f array<double>")
    got = {r["entity"]: r["cluster"] for r in cluster.label(f, [[0.0, 0.0], [4.0, 4.0]], "manhattan").collect()}
    assert got == {1: 0, 2: 1}


def test_segment_clusters_and_labels_by_segment(spark):
    rows = [(s, c, e, [float((e % 2) * 5 + s), 0.0]) for s in (0, 1) for c in "ab" for e in range(20)]
    f = spark.createDataFrame(rows, "segment long, channel string, entity long, f array<double>")
    got = cluster.segment_clusters(f, ClusterSpec(k=2, w=2)).collect()
    assert len(got) == 80 and all(r["cluster"] == r["entity"] % 2 for r in got)
    binned = spark.createDataFrame([(c, e, b, 1, b // 10) for c in "ab" for e in range(4) for b in (1, 11)], "channel string, entity long, bin long, cnt long, segment long")
    labels = spark.createDataFrame([(s, c, e, (e + (c == "b") * s) % 2) for s in (0, 1) for c in "ab" for e in range(4)], "segment long, channel string, entity long, cluster int")
    pairs = {(r["segment"], r["u"], r["v"]) for r in similarity.pairwise_cosine(binned, "a", "b", labels, ("segment",)).collect()}
    assert pairs == {(s, u, v) for s in (0, 1) for u in range(4) for v in range(4) if (u - v - s) % 2 == 0}
    assert metrics.partial_products(binned, "a", "b", labels, ("segment",)).first()["products"] == 16


def test_several_labels_count_a_pair_once(spark):
    binned = spark.createDataFrame([(c, 1, b, 2) for c in "ab" for b in (1, 2)], BINNED)
    labels = spark.createDataFrame([(c, 1, k) for c in "ab" for k in (0, 1)], "channel string, entity long, cluster int")
    assert [(r["dot"], r["sim"]) for r in similarity.pairwise_cosine(binned, "a", "b", labels, several=True).collect()] == [(8, 1.0)]


def test_series_are_numbered_without_a_window_over_all(spark):
    rows = [(c, e, b, 1) for c in "ab" for e in range(150) for b in range(e % 3 + 1)]
    v = embed.series(spark.createDataFrame(rows, BINNED), 4)
    assert sorted(r["i"] for r in v.collect()) == list(range(300))
    d = embed.distances(v.where("i < 30"))
    by = {r["i"]: np.repeat([1, 0], [len(r["bins"]), 4 - len(r["bins"])]) for r in v.where("i < 30").collect()}
    got = {(r["i"], r["j"]): r["d"] for r in d.collect()}
    assert got == {(i, j): dtw.distance(by[i], by[j]) for i in range(30) for j in range(i + 1, 30)}
    w = {(r["i"], r["j"]): r["w"] for r in embed.affinity(v.where("i < 30"), 2.0).collect()}
    assert all(np.isclose(w[k], np.exp(-x / 2)) for k, x in got.items())


def test_distance_of_distributions_without_keys(spark):
    s = [0.1, 0.2, 0.2, 0.4, 0.9]
    frame = spark.createDataFrame([(i, x) for i, x in enumerate(s)], "u long, s double")
    sigma2 = sum(x * x for x in s) / (2 * len(s))
    cdf = lambda x: 1 - np.exp(-x * x / (2 * sigma2))
    want = max(max(abs((i + 1) / 5 - cdf(x)) if i + 1 == 5 or s[i + 1] != x else 0, abs(s.index(x) / 5 - cdf(x))) for i, x in enumerate(s))
    assert np.isclose(likelihood.ks_rayleigh(frame).first()["ks"], want)


def test_segment_mode_takes_pruning_salts_and_sampled_training(spark):
    events, _ = planted_events(spark, SF, 31)
    base = AlignSpec(every_days=7, match=MatchSpec(theta=0.3), train_fraction=1.0)
    plain = align(events, "a", "b", base).pairs.collect()
    hard = align(events, "a", "b", replace(base, prune=True, salts=3)).pairs.collect()
    rounded = lambda rows: sorted((r["u"], r["v"], round(r["score"], 9), r["n_segments"]) for r in rows)
    assert rounded(plain) == rounded(hard) != []
    with pytest.raises(PlanTooLarge):
        align(events, "a", "b", replace(base, most_products=10))


def test_pruning_is_exact_by_both_ways(spark, monkeypatch):
    events, _ = planted_events(spark, SF, 31)
    binned = binning.bin_events(events, binning.HOUR_US)
    plain = sorted((r["u"], r["v"], r["dot"]) for r in similarity.pairwise_cosine(binned, "a", "b", min_sim=0.3).collect())
    for worth in (1.0, -100.0):  # always all products; always prefixes
        monkeypatch.setattr(similarity, "WORTH", worth)
        assert sorted((r["u"], r["v"], r["dot"]) for r in similarity.pairwise_cosine(binned, "a", "b", min_sim=0.3, prune=True).collect()) == plain != []


def test_all_distances_equal_single_ones():
    rng = np.random.default_rng(8)
    for n, m in ((1, 1), (1, 4), (7, 3), (20, 20), (13, 31)):
        x, y = rng.integers(0, 5, (6, n)).astype(float), rng.integers(0, 5, (5, m)).astype(float)
        assert np.array_equal(dtw.all_distances(x, y), [[dtw.distance(a, b) for b in y] for a in x])
