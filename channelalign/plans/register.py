"""The registered queries of the alignment methods: every variant, baseline, measure and workload on the given tables."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import replace
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from channelalign.functions import local_clusters
from channelalign.operators import baselines, binning, cluster, embed, likelihood, matching, metrics, reduced, segments, similarity
from channelalign.operators.binning import DAY_US, HOUR_US
from channelalign.operators.cluster import ClusterSpec
from channelalign.plans.oracle import ORACLES
from channelalign.plans.pipeline import AlignSpec, align, align_all
from channelalign.sources.channels import embedding_features, event_stream, events_channels, lineitem_channels, orders_channel
from channelalign.sources.planted import planted_events, planted_lineitem
from channelalign.sources.shared import shared_dir, written
from channelalign.sources.state import SegmentStore, write_days
from channelalign.streaming import streams

ORIGIN = 1_704_067_200_000_000  # 2024-01-01 UTC, the first day of the events table
BANDS = (55, 70)
CENTROIDS = [[0.2, 0.2, 0.1], [0.5, 0.5, 0.2], [0.8, 0.8, 0.3]]
THETAS = [-5.0, 0.0, 1.0, 5.0, 10.0, 15.0, 20.0, 30.0]
JITTER = 31
LANDMARKS = 400  # for more than MOST_SERIES series

_registered: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f):
    _registered[f.__name__] = f
    return f


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_registered)


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, sql in ORACLES.items() if name in _registered}


def _rounded(c: str, digits: int):
    """F.round(c, digits), which goes by decimals, only where a number is near the middle of two, large, or none at all; elsewhere the nearer one is plain arithmetic."""
    x = F.col(c) * 10.0**digits
    near = F.floor(x + 0.5)
    plain = (F.abs(x) < 2.0**31) & (F.abs(x - near) < 0.4999)
    return F.when(plain, near / 10.0**digits).otherwise(F.round(c, digits)).alias(c)


def rounded(frame: DataFrame, digits: int = 6) -> DataFrame:
    return frame.select(*[_rounded(c, digits) if t == "double" else F.col(c) for c, t in frame.dtypes])


def _twin(spark: SparkSession, sf_dir: str, width_us: int = HOUR_US, jitter: int = JITTER, **how):
    events, truth = planted_events(spark, sf_dir, jitter, **how)
    return events, truth, binning.bin_events(events, width_us)


def _pairs(spark: SparkSession, sf_dir: str, **how) -> DataFrame:
    return similarity.pairwise_cosine(_twin(spark, sf_dir)[2], "a", "b", **how)


# ------------------------------------------------------------------ sources and bins

@query
def profile_channels(spark: SparkSession, sf_dir: str) -> DataFrame:
    every = events_channels(spark, sf_dir).unionByName(orders_channel(spark, sf_dir)).unionByName(lineitem_channels(spark, sf_dir))
    return every.groupBy("channel").agg(F.count(F.lit(1)).alias("n_events"), F.countDistinct("src").alias("n_entities"), F.min("us").alias("first_us"), F.max("us").alias("last_us"))


@query
def profile_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    days = events_channels(spark, sf_dir).withColumn("day", F.floor(F.col("us") / DAY_US))
    rows = days.rollup("channel", "day").agg(F.count(F.lit(1)).alias("n_events"), F.countDistinct("src").alias("n_entities"))
    return rows.fillna({"channel": "all", "day": -1})


@query
def profile_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entities per channel by a sketch that merges over days, beside the exact count."""
    e = events_channels(spark, sf_dir)
    sketches = e.groupBy("channel", F.floor(F.col("us") / DAY_US).alias("day")).agg(F.hll_sketch_agg("src", 12).alias("s"))
    near = sketches.groupBy("channel").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("approx_entities"))
    exact = e.groupBy("channel").agg(F.countDistinct("src").alias("n_entities"))
    return exact.join(near, "channel").select("channel", "n_entities", (F.abs(F.col("approx_entities") - F.col("n_entities")) <= 0.05 * F.col("n_entities") + 1).alias("near_enough"))


@query
def span_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning.span(events_channels(spark, sf_dir), HOUR_US)


@query
def bin_events_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning.bin_events(events_channels(spark, sf_dir), HOUR_US)


@query
def bin_events_3s(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning.bin_events(events_channels(spark, sf_dir), 3_000_000)


@query
def bin_lineitem_source_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning.bin_events(lineitem_channels(spark, sf_dir), 30 * DAY_US)


@query
def bin_lineitem_target_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning.bin_events(lineitem_channels(spark, sf_dir), 30 * DAY_US, role="target")


@query
def bin_lineitem_both_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning.bin_events(lineitem_channels(spark, sf_dir, "l_linestatus"), 30 * DAY_US, role="both")


@query
def bin_stream_equiv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bins of day files that are read as a stream."""
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    write_days(events_channels(spark, sf_dir), f"{base}/days")
    streams.incremental_bins(event_stream(spark, f"{base}/days", 10), HOUR_US, f"{base}/bins", f"{base}/checkpoint")
    return streams.read_incremental_bins(spark, f"{base}/bins")


@query
def planted_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planted_events(spark, sf_dir, JITTER)[1]


@query
def sparsity(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = events_channels(spark, sf_dir)
    return rounded(binning.sparsity(binning.bin_events(e, HOUR_US), binning.span(e, HOUR_US)), 9)


@query
def vectors_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = binning.to_vectors(binning.bin_events(events_channels(spark, sf_dir, ("view", "click")), DAY_US))
    return v.select("channel", "entity", F.array_join("bins", ",").alias("bins"), F.array_join("cnts", ",").alias("cnts"), "sq_norm", "n_events")


# ------------------------------------------------------------------ features

def _binned_events(spark: SparkSession, sf_dir: str):
    e = events_channels(spark, sf_dir)
    return binning.bin_events(e, HOUR_US, with_first=True), binning.span(e, HOUR_US)


@query
def avg_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    b, s = _binned_events(spark, sf_dir)
    return rounded(reduced.average_count(b, s).join(reduced.average_count(b, s, "active").withColumnRenamed("aec", "aec_active"), ["channel", "entity"]), 9)


@query
def edge_delta_abs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(reduced.edge_delta(*_binned_events(spark, sf_dir)), 9)


@query
def edge_delta_signed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(reduced.edge_delta(*_binned_events(spark, sf_dir), mode="signed"), 9)


@query
def first_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reduced.first_event(*_binned_events(spark, sf_dir))


def _flat(features: DataFrame) -> DataFrame:
    return features.select("channel", "entity", *[F.round(F.col("f")[i], 9).alias(f"f{i}") for i in range(3)])


@query
def reduced_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(reduced.reduced_features(events_channels(spark, sf_dir), HOUR_US))


@query
def reduced_with_attributes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A further attribute from the events' JSON column."""
    from channelalign.sources.tables import load

    e = load(spark, sf_dir, "events")
    extra = e.groupBy(F.col("event_type").alias("channel"), F.col("user_id").alias("entity")).agg(F.avg(F.get_json_object("props", "$.k").cast("long")).alias("k"))
    f = reduced.with_attributes(reduced.reduced_features(events_channels(spark, sf_dir), HOUR_US), extra, ["k"])
    return f.select("channel", "entity", *[F.round(F.col("f")[i], 9).alias(f"f{i}") for i in range(4)])


def _conversation_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.sources.tables import load

    c = load(spark, sf_dir, "conversations")
    binned = c.groupBy(F.col("role").alias("channel"), F.col("conv_id").alias("entity"), F.col("turn").alias("bin")).agg(F.count(F.lit(1)).alias("cnt"))
    longest = binned.agg(F.max("bin")).first()[0] or 0
    return embed.series(binned, max(32, longest + 2))  # the length of all: zeros at the end of both cost nothing


@query
def dtw_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Affinity of short series: all conversations as entities, roles as channels, turns as bins. The rows grow with the square of the series."""
    return rounded(embed.affinity(_conversation_series(spark, sf_dir), 5.0))


@query
def affinity_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Warping distances and affinities of all conversations, side by side."""
    d = embed.distances(_conversation_series(spark, sf_dir))
    return rounded(d.withColumn("w", F.exp(-F.col("d") / 5.0)))


@query
def laplacian_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Laplacian of the channels of the events table: numbered by name, their affinity the cosine of their totals per hour."""
    e = events_channels(spark, sf_dir)
    binned = binning.bin_events(e, HOUR_US)
    names = binned.select("channel").distinct().withColumn("i", (F.row_number().over(Window.orderBy("channel")) - 1).cast("long"))  # a few rows
    alike = similarity.channel_correlation(binned, binning.span(e, HOUR_US))
    w = alike.join(names.withColumnRenamed("channel", "left"), "left").join(names.toDF("right", "j"), "right").select("i", "j", F.col("cos").alias("w"))
    return rounded(embed.laplacian(w))


@query
def laplacian_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Laplacian of the affinity of all conversations; laplacian_small is that of the few channels of the events."""
    return rounded(embed.laplacian(embed.affinity(_conversation_series(spark, sf_dir), 5.0)))


@query
def eigenmap_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations: exact up to MOST_SERIES series, by LANDMARKS of them (approximate) beyond."""
    return _flat(embed.eigenmap(_conversation_series(spark, sf_dir), 3, 5.0, landmarks=LANDMARKS, exact_to=embed.MOST_SERIES))


@query
def eigenmap_landmarks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flat(embed.eigenmap(_conversation_series(spark, sf_dir), 3, 5.0, landmarks=20))


# ------------------------------------------------------------------ clusters

@query
def partition_subsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = events_channels(spark, sf_dir).select("channel", F.col("src").alias("entity")).distinct()
    return cluster.assign_subsets(ids, 22, 7, portable=True)


@query
def label_nearest_fixed_centroids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cluster.label(reduced.reduced_features(events_channels(spark, sf_dir), HOUR_US), CENTROIDS)


@query
def rep_clusters_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    events, _ = planted_events(spark, sf_dir, JITTER, profile=True)
    return cluster.representative_clusters(reduced.reduced_features(events, HOUR_US))[0]


def _quality(spark: SparkSession, sf_dir: str, runs: dict) -> DataFrame:
    gold = embedding_features(spark, sf_dir)
    out = None
    for name, labels in runs.items():
        row = metrics.clustering_quality(gold, labels(gold), gold).select(F.lit(name).alias("method"), "inertia", "purity", "adjusted_rand")
        out = row if out is None else out.unionByName(row)
    return rounded(out, 4)


@query
def rep_clusters_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Representatives by means, count-weighted means, mixture samples, moment draws, several rounds and channels apart."""
    base = ClusterSpec(k=10, w=4)
    variants = {
        "means": base, "counted_means": ClusterSpec(k=10, w=4, weight="count"), "moments": ClusterSpec(k=10, w=4, representative="moments", n_samples=60),
        "three_rounds": ClusterSpec(k=10, w=4, rounds=3), "literal_subsets": ClusterSpec(k=10, w=64, subsets="literal"), "channels_apart": ClusterSpec(k=10, w=4, joint=False), "cosine": ClusterSpec(k=10, w=4, distance="cosine"),
    }
    return _quality(spark, sf_dir, {n: (lambda f, s=s: cluster.representative_clusters(f, s)[0]) for n, s in variants.items()})


@query
def gmm_clusters_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mixture samples as representatives, on all dimensions with diagonal covariances."""
    spec = ClusterSpec(k=10, w=2, method=partial(local_clusters.mixture, n_samples=60, diagonal=True))
    return _quality(spark, sf_dir, {"mixture_samples": lambda f: cluster.representative_clusters(f, spec)[0]})


@query
def baseline_clusters_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _quality(spark, sf_dir, {
        "direct_kmeans": lambda f: baselines.direct_kmeans(f, 10)[0], "direct_mixture": lambda f: baselines.direct_gmm(f, 10),
        "sample_then_label": lambda f: baselines.sample_then_label(f, 10, 0.3)[0],
    })


def _banded(spark: SparkSession, sf_dir: str):
    binned = _twin(spark, sf_dir)[2]
    return binned, cluster.activity_bands(binned, BANDS)


@query
def cluster_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(cluster.balance(_banded(spark, sf_dir)[1]), 9)


@query
def comparisons_kept(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(metrics.comparisons(_banded(spark, sf_dir)[1], "a", "b"), 9)


@query
def partial_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    binned, labels = _banded(spark, sf_dir)
    return metrics.partial_products(binned, "a", "b", labels)


@query
def cocluster_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(metrics.cocluster_recall(_banded(spark, sf_dir)[1], planted_events(spark, sf_dir, JITTER)[1], "a", "b"), 9)


# ------------------------------------------------------------------ similarity

@query
def cosine_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(similarity.every_cosine(_twin(spark, sf_dir)[2], "a", "b"), 9)


@query
def cosine_within_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    binned, labels = _banded(spark, sf_dir)
    return rounded(similarity.every_cosine(binned, "a", "b", labels), 9)


@query
def cosine_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(similarity.block_cosine(binning.to_vectors(_twin(spark, sf_dir)[2]), "a", "b"), 9)


@query
def cosine_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(similarity.every_cosine(_twin(spark, sf_dir)[2], "a", "b", salts=4, hot=20), 9)


@query
def cosine_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_pairs(spark, sf_dir, min_sim=0.3, prune=True), 9)


@query
def cosine_all_channels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(similarity.all_pairs_cosine(binning.bin_events(events_channels(spark, sf_dir, ("view", "click", "purchase")), HOUR_US), min_sim=0.2), 9)


@query
def cosine_every_channel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs of all channels; cosine_all_channels has the three channels and the least similarity of its SQL."""
    return rounded(similarity.all_pairs_cosine(binning.bin_events(events_channels(spark, sf_dir), HOUR_US)), 9)


@query
def jaccard_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(similarity.pairwise_jaccard(_twin(spark, sf_dir)[2], "a", "b"), 9)


@query
def near_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similarity.near_counts(planted_events(spark, sf_dir, JITTER)[0], "a", "b", 62_000_000)


@query
def last_before(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similarity.last_before(events_channels(spark, sf_dir), "view", "click").fillna({"before_us": -1})


@query
def channel_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = events_channels(spark, sf_dir).unionByName(planted_events(spark, sf_dir, JITTER)[0])
    return rounded(similarity.channel_correlation(binning.bin_events(e, HOUR_US), binning.span(e, HOUR_US)))


# ------------------------------------------------------------------ matches

def _matches(spark: SparkSession, sf_dir: str, how: str = "intersect", **rule) -> DataFrame:
    return similarity.matched_cosine(_twin(spark, sf_dir)[2], "a", "b", how, **rule)


def _chosen(spark: SparkSession, sf_dir: str, how: str, **rule) -> DataFrame:
    return rounded(_matches(spark, sf_dir, how, **rule).select("u", "v", "sim"), 9)


@query
def match_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chosen(spark, sf_dir, "intersect", rule="threshold", theta=0.5)


@query
def match_best(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chosen(spark, sf_dir, "intersect", rule="best", theta=0.3)


@query
def match_top3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chosen(spark, sf_dir, "intersect", rule="top", m=3)


@query
def forward(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chosen(spark, sf_dir, "forward")


@query
def backward(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chosen(spark, sf_dir, "backward")


@query
def reconciled(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = _pairs(spark, sf_dir)
    return matching.reconcile_sets(matching.forward(pairs), matching.backward(pairs))


@query
def reconciled_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chosen(spark, sf_dir, "union")


# ------------------------------------------------------------------ likelihood and segments

def _weekly(spark: SparkSession, sf_dir: str):
    events, truth = planted_events(spark, sf_dir, JITTER)
    binned = binning.bin_events(events, HOUR_US, ORIGIN)
    return segments.plan(binned, segments.segment_of_bin(HOUR_US, 7)), truth


def _h1(spark: SparkSession, sf_dir: str) -> DataFrame:
    binned, _ = _weekly(spark, sf_dir)
    best = similarity.matched_cosine(binned, "a", "b", "forward", "top", m=1, keys=("segment",))
    return likelihood.h1_maxima(best, likelihood.entities(binned, "a", "u", ("segment",)), ("segment",))


def _h0(spark: SparkSession, sf_dir: str, m: int | str = 10, scope: str = "row", axis: str = "u") -> DataFrame:
    binned, _ = _weekly(spark, sf_dir)
    keys = ("segment",)
    pairs = similarity.matched_cosine(binned, "a", "b", "forward", "top", m=2, keys=keys) if m == "matched" else similarity.asked_cosine(binned, "a", "b", keys)
    return likelihood.h0_maxima(pairs, likelihood.entities(binned, "a", "u", keys), likelihood.entities(binned, "b", "v", keys), m, 0, scope, axis, keys)


def _maxima(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return _h1(spark, sf_dir), _h0(spark, sf_dir)


@query
def h1_maxima(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_h1(spark, sf_dir), 9)


@query
def h0_maxima(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_h0(spark, sf_dir), 9)


@query
def h0_matched(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_h0(spark, sf_dir, "matched"), 9)


@query
def h0_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_h0(spark, sf_dir, 10, "pool"), 9)


@query
def h0_by_right(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_h0(spark, sf_dir, 10, "row", "v"), 9)


@query
def rayleigh_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(likelihood.fit_model(*_maxima(spark, sf_dir), ("segment",)))


@query
def rayleigh_hist(spark: SparkSession, sf_dir: str) -> DataFrame:
    h1, h0 = _maxima(spark, sf_dir)
    return rounded(likelihood.distribution(h1.where("segment = 1"), h0.where("segment = 1"), 20))


@query
def rayleigh_hist_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The histograms of all weeks; rayleigh_hist has the one week of its SQL."""
    return rounded(likelihood.distribution(*_maxima(spark, sf_dir), 20, ("segment",)))


@query
def rayleigh_ks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(likelihood.ks_rayleigh(_h1(spark, sf_dir), ("segment",)))


@query
def overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = likelihood.fit_model(*_maxima(spark, sf_dir), ("segment",))
    return rounded(m.select("segment", likelihood.overlap(F.col("sigma1"), F.col("sigma0")).alias("overlap")))


@query
def overlap_calibrated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overlap of planted and native channels: with m draws, with the matched null, and of best similarities before and after one channel's bins are moved."""
    out = None
    for name, events, (left, right) in (("planted", planted_events(spark, sf_dir, JITTER)[0], ("a", "b")), ("native", events_channels(spark, sf_dir, ("view", "click")), ("view", "click"))):
        binned, spans = binning.bin_events(events, HOUR_US, ORIGIN), binning.span(events, HOUR_US, ORIGIN)
        pairs = similarity.pairwise_cosine(binned, left, right)
        us, vs = likelihood.entities(binned, left, "u"), likelihood.entities(binned, right, "v")
        h1 = likelihood.h1_maxima(pairs, us)
        moved = likelihood.h1_maxima(similarity.pairwise_cosine(likelihood.shuffled_null(binned, right, spans), left, right), us)
        for kind, h0 in (("draws", likelihood.h0_maxima(pairs, us, vs)), ("matched", likelihood.h0_maxima(pairs, us, vs, "matched")), ("moved", moved)):
            row = likelihood.fit_model(h1, h0).select(F.lit(name).alias("channels"), F.lit(kind).alias("null_kind"), likelihood.overlap(F.col("sigma1"), F.col("sigma0")).alias("overlap"))
            out = row if out is None else out.unionByName(row)
    return rounded(out, 4)


def _scored(spark: SparkSession, sf_dir: str, **how):
    binned, truth = _weekly(spark, sf_dir)
    return segments.score_segments(binned, "a", "b", **how), truth


@query
def score_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_scored(spark, sf_dir)[0].select("segment", "u", "v", "score"))


@query
def score_forms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The log density alone and the log posterior, for the second week."""
    a = _scored(spark, sf_dir, form="log_p1")[0].where("segment = 1").select("u", "v", F.col("score").alias("log_p1"))
    b = _scored(spark, sf_dir, form="posterior")[0].where("segment = 1").select("u", "v", F.col("score").alias("log_posterior"))
    return rounded(a.join(b, ["u", "v"]))


@query
def score_forms_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The log density alone and the log posterior, of all weeks; score_forms has the one week of its SQL."""
    a, b = (_scored(spark, sf_dir, form=form)[0].select("segment", "u", "v", F.col("score").alias(name)) for form, name in (("log_p1", "log_p1"), ("posterior", "log_posterior")))
    return rounded(a.join(b, ["segment", "u", "v"]))


@query
def score_accumulated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(segments.accumulate(_scored(spark, sf_dir)[0]))


@query
def score_absent_zero(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(segments.accumulate(_scored(spark, sf_dir, absent="active_zero")[0]))


@query
def score_trajectory(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(segments.trajectory(_scored(spark, sf_dir)[0]))


@query
def score_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(segments.matches(segments.accumulate(_scored(spark, sf_dir)[0]), 1.0).select("u", "v", "score"))


def _store(spark: SparkSession) -> SegmentStore:
    return SegmentStore(spark, f"{shared_dir(spark)}/state-{uuid.uuid4().hex}")


@query
def incremental_equals_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The state of the segment loop; its SQL is that of the one-shot form."""
    binned, _ = _weekly(spark, sf_dir)
    found = sorted(r[0] for r in binned.select("segment").distinct().collect())
    return rounded(segments.run_all(binned, "a", "b", found, _store(spark)))


@query
def stream_equals_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The state of a stream of weekly files."""
    base, store = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", _store(spark)
    events, _ = planted_events(spark, sf_dir, JITTER)
    shifted = events.withColumn("us", F.col("us") - ORIGIN).withColumn("week", F.floor(F.col("us") / (7 * DAY_US)))
    for n in sorted(r[0] for r in shifted.select("week").distinct().collect()):  # files arrive week by week
        shifted.where(F.col("week") == n).drop("week").coalesce(1).write.mode("append").parquet(f"{base}/weeks")
    streams.start(event_stream(spark, f"{base}/weeks", 1), store, "a", "b", HOUR_US, 7, f"{base}/checkpoint").awaitTermination()
    return rounded(store.read())


@query
def stream_split_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The state of a stream whose weeks come in two files each, a week's second half after the next week's first: late rows revise their segment's scores."""
    base, store = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", _store(spark)
    events, _ = planted_events(spark, sf_dir, JITTER)
    shifted = events.withColumn("us", F.col("us") - ORIGIN).withColumn("week", F.floor(F.col("us") / (7 * DAY_US))).withColumn("half", F.pmod(F.col("key"), F.lit(2)))
    weeks = sorted(r[0] for r in shifted.select("week").distinct().collect())  # a few numbers
    for n in range(len(weeks) + 1):
        wanted = [(w, h) for w, h in ((weeks[n] if n < len(weeks) else None, 0), (weeks[n - 1] if n else None, 1)) if w is not None]
        here = F.lit(False)
        for w, h in wanted:
            here |= (F.col("week") == w) & (F.col("half") == h)
        shifted.where(here).drop("week", "half").coalesce(1).write.mode("append").parquet(f"{base}/weeks")
    streams.start(event_stream(spark, f"{base}/weeks", 1), store, "a", "b", HOUR_US, 7, f"{base}/checkpoint", compact_every=2).awaitTermination()
    return rounded(store.read())


# ------------------------------------------------------------------ measures and baselines

@query
def metrics_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(metrics.summary(_matches(spark, sf_dir), planted_events(spark, sf_dir, JITTER)[1]), 9)


@query
def metrics_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Missed shares by side, unit and stage (final matches, or each direction's own before they are reconciled)."""
    pairs, truth = _pairs(spark, sf_dir), planted_events(spark, sf_dir, JITTER)[1]
    final, fwd, bwd = matching.reconcile(pairs), matching.forward(pairs), matching.backward(pairs)
    out = None
    for stage, side, unit, found in (("final", "forward", "entity", final), ("final", "backward", "entity", final), ("final", "forward", "pair", final), ("directional", "forward", "entity", fwd), ("directional", "backward", "entity", bwd)):
        row = metrics.not_matched(found, truth, side, unit).select(F.lit(stage).alias("stage"), F.lit(side).alias("side"), F.lit(unit).alias("unit"), "n_true", "n_missed", "accuracy")
        out = row if out is None else out.unionByName(row)
    return rounded(out, 9)


@query
def metrics_sweep_weekly(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored, truth = _scored(spark, sf_dir)
    state = segments.accumulate(scored).withColumn("score", F.round("score", 6))
    return rounded(metrics.sweep(state, truth, THETAS), 9)


def _monthly(spark: SparkSession, sf_dir: str):
    events, truth = planted_lineitem(spark, sf_dir)
    return segments.plan(binning.bin_events(events, DAY_US, 0), segments.month_of_day_bin(0)), truth


@query
def metrics_sweep_monthly_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    binned, truth = _monthly(spark, sf_dir)
    state = segments.accumulate(segments.score_segments(binned, "a", "b")).withColumn("score", F.round("score", 6))
    return rounded(metrics.sweep(state, truth, THETAS), 9)


@query
def metrics_sweep_28d_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers in segments of 28 days."""
    events, truth = planted_lineitem(spark, sf_dir)
    binned = segments.plan(binning.bin_events(events, DAY_US, 0), segments.segment_of_bin(DAY_US, 28))
    state = segments.accumulate(segments.score_segments(binned, "a", "b")).withColumn("score", F.round("score", 6))
    return rounded(metrics.sweep(state, truth, THETAS), 9)


@query
def jaccard_found_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(metrics.jaccard(_matches(spark, sf_dir), planted_events(spark, sf_dir, JITTER)[1]), 9)


@query
def random_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    binned = _twin(spark, sf_dir)[2]
    found = baselines.random_match(likelihood.entities(binned, "a", "u"), likelihood.entities(binned, "b", "v"))
    return rounded(metrics.summary(found, planted_events(spark, sf_dir, JITTER)[1]), 9)


@query
def negative_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Channels without a common signal: hardly a match is right, whatever its score."""
    binned = segments.plan(binning.bin_events(events_channels(spark, sf_dir, ("view", "click")), HOUR_US, ORIGIN), segments.segment_of_bin(HOUR_US, 7))
    state = segments.accumulate(segments.score_segments(binned, "view", "click")).withColumn("score", F.round("score", 6))
    ids = binned.select(F.col("entity").alias("u"), F.col("entity").alias("v")).distinct()
    return rounded(metrics.sweep(state, ids, THETAS), 9)


# ------------------------------------------------------------------ pipelines and workloads

def _run(spark: SparkSession, sf_dir: str, spec: AlignSpec, **how) -> DataFrame:
    events, truth = planted_events(spark, sf_dir, **how)
    return rounded(metrics.summary(align(events, "a", "b", spec).matches, truth), 9)


@query
def pipeline_unclustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    events, _ = planted_events(spark, sf_dir, JITTER)
    return rounded(align(events, "a", "b").matches.select("u", "v", "dot", "sim"), 9)


@query
def pipeline_three_ways(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No clustering, reduced feature, embedded feature: accuracy, comparisons kept and products of each (k = 5, w = 22). The embedding is exact up to MOST_SERIES series, by landmarks (approximate) beyond."""
    events, truth = planted_events(spark, sf_dir, JITTER, profile=True)
    out = None
    for feature in (None, "reduced", "embedded"):
        got = align(events, "a", "b", AlignSpec(feature=feature, most_bins=60, landmarks=LANDMARKS, exact_to=embed.MOST_SERIES))
        labels = got.labels if got.labels is not None else got.binned.select("channel", "entity", F.lit(0).alias("cluster")).distinct()
        row = metrics.summary(got.matches, truth).select("ma", "fnma", "bnma").crossJoin(metrics.comparisons(labels, "a", "b").select("kept_share")).crossJoin(metrics.partial_products(got.binned, "a", "b", labels).select("products")).crossJoin(metrics.cocluster_recall(labels, truth, "a", "b").select(F.col("recall").alias("together"))).withColumn("feature", F.lit(feature or "none"))
        out = row if out is None else out.unionByName(row)
    return rounded(out, 4)


@query
def pipeline_all_channels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(align_all(events_channels(spark, sf_dir)).select("left", "right", "u", "v", "sim"), 9)


@query
def pipeline_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, AlignSpec(every_days=7, score_theta=1.0), jitter_s=JITTER)


def _banded_run(spark: SparkSession, sf_dir: str):
    events, truth = planted_events(spark, sf_dir, JITTER)
    return events, truth, cluster.activity_bands(binning.bin_events(events, HOUR_US, 0), BANDS)


@query
def pipeline_segments_clustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weekly segments, compared within activity bands, models trained on a fifth of the left entities."""
    events, truth, labels = _banded_run(spark, sf_dir)
    return rounded(metrics.summary(align(events, "a", "b", AlignSpec(every_days=7, score_theta=1.0, train_fraction=0.2), labels).matches, truth), 9)


@query
def products_segments_clustered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Products of the weekly joins: all pairs, those within bands, and those of the training sample."""
    events, _, labels = _banded_run(spark, sf_dir)
    planned = segments.plan(binning.bin_events(events, HOUR_US, 0), segments.segment_of_bin(HOUR_US, 7))
    sample = likelihood.training_sample(planned, "a", "b", 0.2)
    made = [metrics.partial_products(b, "a", "b", own, ("segment",)).select(F.col("products").alias(name)) for name, b, own in (("unclustered", planned, None), ("clustered", planned, labels), ("training", sample, None))]
    return made[0].crossJoin(made[1]).crossJoin(made[2])


@query
def pipeline_segments_own_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A whole run for each week: features and clusters of the week's own events, its pairs, its model."""
    return _run(spark, sf_dir, AlignSpec(every_days=7, score_theta=1.0, feature="reduced", per_segment=True, cluster=ClusterSpec(k=3)), jitter_s=JITTER)


def _ways(spark: SparkSession, events: DataFrame, truth: DataFrame, runs: dict[str, AlignSpec]) -> DataFrame:
    """For each run: measures, products and seconds from events to matches, and how many times as fast as the first run it is."""
    rows, first = None, None
    for name, spec in runs.items():
        began = time.perf_counter()
        got = align(events, "a", "b", spec)
        found = written(got.matches.select("u", "v"), "matches")
        seconds = time.perf_counter() - began
        first = seconds if first is None else first
        keys = ("segment",) if spec.every_days is not None else ()
        row = metrics.summary(found, truth).select("n_found", "n_right", "ma", "fnma", "bnma").crossJoin(metrics.partial_products(got.binned, "a", "b", got.labels, keys).select("products"))
        row = row.select(F.lit(name).alias("way"), "*", F.lit(seconds).alias("seconds"), F.lit(first / seconds).alias("speed_up"))
        rows = row if rows is None else rows.unionByName(row)
    return rounded(rows, 4)


@query
def table_three_ways(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bins of 3 s, a second of jitter, k = 5, w = 22: no clustering, the reduced feature, the embedded one (by LANDMARKS landmarks where there are more series), with seconds and speed-up."""
    events, truth = planted_events(spark, sf_dir, 1, profile=True)
    base = AlignSpec(width_us=3_000_000, most_bins=60, landmarks=LANDMARKS)
    return _ways(spark, events, truth, {name: replace(base, feature=feature) for name, feature in (("none", None), ("reduced", "reduced"), ("embedded", "embedded"))})


def _growing(spark: SparkSession, frames, every_days: int, width_us: int) -> DataFrame:
    out = None
    for share in (0.25, 0.5, 1.0):
        events, truth = frames(share)
        base = AlignSpec(width_us=width_us, every_days=every_days, score_theta=1.0)
        rows = _ways(spark, events, truth, {"none": base, "reduced": replace(base, feature="reduced"), "reduced_by_segment": replace(base, feature="reduced", per_segment=True)}).withColumn("share", F.lit(share))
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def scale_parts_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quarter, half and all of the parts in segments of 90 days, clustered (over all, by segment) and not: measures, products, seconds."""
    return _growing(spark, lambda share: planted_lineitem(spark, sf_dir, "l_partkey", share=share), 90, DAY_US)


@query
def scale_users_weekly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quarter, half and all of the users in weekly segments, clustered (over all, by segment) and not: measures, products, seconds."""
    n = planted_events(spark, sf_dir, JITTER)[0].where("channel = 'a'").agg(F.max("src")).first()[0] or 0
    return _growing(spark, lambda share: planted_events(spark, sf_dir, JITTER, profile=True, users=int((n + 1) * share) + 1), 7, HOUR_US)


@query
def ablation_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numbers of clusters and subsets, and labels of the two nearest centroids: what is kept, what stays together, and the measures."""
    events, truth = planted_events(spark, sf_dir, JITTER, profile=True)
    binned, features = binning.bin_events(events, HOUR_US), written(reduced.reduced_features(events, HOUR_US), "features")
    out = None
    for k, w, nearest in ((2, 22, 1), (5, 5, 1), (5, 22, 1), (5, 50, 1), (10, 22, 1), (5, 22, 2)):
        labels = written(cluster.representative_clusters(features, ClusterSpec(k=k, w=w, nearest=nearest))[0], "labels")
        together = truth.join(labels.where("channel = 'a'").select(F.col("entity").alias("u"), "cluster"), "u").join(labels.where("channel = 'b'").select(F.col("entity").alias("v"), "cluster"), ["v", "cluster"]).select("u", "v").distinct().agg(F.count(F.lit(1)).alias("together"))
        found = similarity.matched_cosine(binned, "a", "b", labels=labels, several=nearest > 1)
        row = metrics.summary(found, truth).select("ma", "fnma", "bnma").crossJoin(metrics.comparisons(labels, "a", "b").select("kept_share")).crossJoin(together)
        row = row.select(F.lit(k).alias("k"), F.lit(w).alias("w"), F.lit(nearest).alias("nearest"), "*")
        out = row if out is None else out.unionByName(row)
    return rounded(out, 4)


@query
def sensitivity_width(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bin width against jitter."""
    out = None
    for jitter in (1, 31):
        events, truth = planted_events(spark, sf_dir, jitter)
        for seconds in (3, 60, 3600, 21600):
            row = metrics.summary(align(events, "a", "b", AlignSpec(width_us=seconds * 1_000_000)).matches, truth).select(F.lit(jitter).alias("jitter_s"), F.lit(seconds).alias("width_s"), "n_found", "ma", "fnma", "bnma")
            out = row if out is None else out.unionByName(row)
    return rounded(out, 9)


@query
def scale_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quarter, half and all of the parts over the whole history, clustered and not: products and accuracy."""
    out = None
    for share in (0.25, 0.5, 1.0):
        events, truth = planted_lineitem(spark, sf_dir, "l_partkey", share=share)
        binned = written(binning.bin_events(events, DAY_US), "bins")
        labels = written(cluster.representative_clusters(reduced.reduced_features(events, DAY_US))[0], "labels")
        for name, own in (("none", None), ("reduced", labels)):
            found = matching.reconcile(similarity.pairwise_cosine(binned, "a", "b", own))
            row = metrics.summary(found, truth).select("ma", "fnma", "bnma").crossJoin(metrics.partial_products(binned, "a", "b", own).select("products")).select(F.lit(share).alias("share"), F.lit(name).alias("clustering"), "products", "ma", "fnma", "bnma")
            out = row if out is None else out.unionByName(row)
    return rounded(out, 4)


@query
def ablation_matching(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the intersection and the rules buy, in the hard setting (3 s bins, 31 s jitter)."""
    events, truth = planted_events(spark, sf_dir, JITTER)
    pairs = similarity.pairwise_cosine(binning.bin_events(events, 3_000_000), "a", "b")
    out = None
    for name, how in (("intersect", {"how": "intersect"}), ("union", {"how": "union"}), ("forward", {"how": "forward"}), ("backward", {"how": "backward"}), ("top2", {"rule": "top", "m": 2}), ("threshold", {"rule": "threshold", "theta": 0.04})):
        row = metrics.summary(matching.reconcile(pairs, **how), truth).select(F.lit(name).alias("way"), "n_found", "n_right", "ma", "fnma", "bnma")
        out = row if out is None else out.unionByName(row)
    return rounded(out, 9)


