"""End-to-end alignment."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.operators import cluster, embed, likelihood, matching, metrics, reduced, segments, similarity
from channelalign.operators.binning import DAY_US, HOUR_US, bin_events, span
from channelalign.operators.cluster import ClusterSpec
from channelalign.sources.shared import written


@dataclass(frozen=True)
class MatchSpec:
    theta: float | None = None
    rule: str = "best"
    m: int = 1
    how: str = "intersect"


@dataclass(frozen=True)
class AlignSpec:
    """feature: None (no clustering), 'reduced', 'embedded' or 'given' (labels are handed to align). every_days: segments with likelihood scores, or None. score_theta: least accumulated score. exact_to: landmarks serve only for more series than that.

    With segments, per_segment makes features and clusters of every segment's own range (reduced only);
    train_fraction is the share of left entities that each segment's model is trained on (None: all where nothing is
    clustered, segments.TRAINED otherwise); match.theta is the least similarity of a pair to be scored. prune and
    salts hold with and without segments; salts 0 takes as many as keep a bin's products near ``hot``.
    """

    width_us: int = HOUR_US
    origin_us: int | None = None
    role: str = "source"
    feature: str | None = None
    cluster: ClusterSpec = field(default_factory=ClusterSpec)
    match: MatchSpec = field(default_factory=MatchSpec)
    every_days: int | None = None
    score_theta: float = 0.0
    m: int | str = 10
    tau: float = 50.0
    dimensions: int = 3
    most_bins: int = 240
    landmarks: int | None = None
    exact_to: int = 0
    prune: bool = False
    salts: int = 0
    hot: int = 10_000_000
    most_products: int | None = None
    per_segment: bool = False
    train_fraction: float | None = None


@dataclass
class AlignResult:
    matches: DataFrame
    pairs: DataFrame
    labels: DataFrame | None
    binned: DataFrame


class PlanTooLarge(RuntimeError):
    """The similarity join would make more rows than allowed."""


def labels_for(events: DataFrame, binned: DataFrame, spec: AlignSpec) -> DataFrame | None:
    """Cluster labels by the chosen feature, of all events."""
    if spec.feature is None:
        return None
    binned = binned.select("channel", "entity", "bin", "cnt")
    if spec.feature == "reduced":
        features = reduced.reduced_features(events, spec.width_us, origin_us=spec.origin_us, role=spec.role)
    elif spec.feature == "embedded":
        n_bins = span(events, spec.width_us, spec.origin_us).first()["n_bins"]
        coarse, n = embed.coarsen(binned, n_bins, spec.most_bins)
        features = embed.eigenmap(embed.series(coarse, n), spec.dimensions, spec.tau, landmarks=spec.landmarks, exact_to=spec.exact_to)
    else:
        raise ValueError(f"no feature {spec.feature}")
    return cluster.representative_clusters(features, spec.cluster)[0]


def estimate(binned: DataFrame, left: str, right: str, labels: DataFrame | None = None, keys: tuple[str, ...] = ()) -> dict[str, int]:
    """Rows that the similarity join will make, before it is started."""
    return metrics.partial_products(binned, left, right, labels, keys).first().asDict()


def _training_products(planned: DataFrame, left: str, right: str, fraction: float) -> int:
    sample = likelihood.training_sample(planned, left, right, fraction)
    return estimate(sample, left, right, None, ("segment",))["products"]


def align(events: DataFrame, left: str, right: str, spec: AlignSpec = AlignSpec(), labels: DataFrame | None = None) -> AlignResult:
    """Matches between two channels; see AlignSpec for the stages that can be switched. labels: channel, entity, cluster and, if they differ by segment, segment; they take the place of the clustering."""
    events = events.where(F.col("channel").isin(left, right))
    if spec.every_days is not None and spec.origin_us is None:
        spec = replace(spec, origin_us=0)
    binned = bin_events(events, spec.width_us, spec.origin_us, spec.role)
    keys: tuple[str, ...] = ()
    if spec.every_days is not None:
        keys = ("segment",)
        binned = segments.plan(binned, segments.segment_of_bin(spec.width_us, spec.every_days, spec.origin_us))
    if labels is None and spec.per_segment and spec.feature is not None:
        if spec.feature != "reduced" or not keys:
            raise ValueError("clusters of segments need segments and the reduced feature")
        labels = written(cluster.segment_clusters(reduced.segment_features(binned, spec.every_days * DAY_US // spec.width_us), spec.cluster), "labels")
    elif labels is None and spec.feature is not None:
        labels = written(labels_for(events, binned, spec), "labels")
    salts = spec.salts
    if spec.most_products is not None or salts == 0:
        made = estimate(binned, left, right, labels, keys)
        salts = salts or max(1, min(1024, -(-made["busiest"] // spec.hot)))
        total = made["products"]
        if keys and (labels is not None or spec.match.theta is not None) and spec.most_products is not None:
            total += _training_products(binned, left, right, spec.train_fraction or segments.TRAINED)
        if spec.most_products is not None and total > spec.most_products:
            raise PlanTooLarge(f"{total} products are over {spec.most_products}: use more clusters, smaller bins, segments or pruning")
    if keys:
        scored = segments.score_segments(binned, left, right, labels, m=spec.m, min_sim=spec.match.theta, prune=spec.prune, salts=salts, left_fraction=spec.train_fraction)
        state = segments.accumulate(scored)
        return AlignResult(segments.matches(state, spec.score_theta, spec.match.rule, spec.match.how, spec.match.m), state, labels, binned)
    pairs = similarity.pairwise_cosine(binned, left, right, labels, min_sim=spec.match.theta, prune=spec.prune and spec.match.theta is not None, salts=salts, hot=spec.hot)
    found = matching.reconcile(pairs, spec.match.how, spec.match.rule, spec.match.theta, spec.match.m)
    return AlignResult(found, pairs, labels, binned)


def align_all(events: DataFrame, spec: AlignSpec = AlignSpec()) -> DataFrame:
    """left, right, u, v, sim of the matches of every two channels; bins and clusters are made once for all."""
    binned = bin_events(events, spec.width_us, spec.origin_us, spec.role)
    pairs = similarity.all_pairs_cosine(binned, labels_for(events, binned, spec))
    return matching.reconcile(pairs, spec.match.how, spec.match.rule, spec.match.theta, spec.match.m, keys=("left", "right"))
