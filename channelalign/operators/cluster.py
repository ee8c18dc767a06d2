"""Clustering by representative points: random subsets, local clusters, one global clustering, labels in one pass.

Features are (channel, entity, f). Labels are (channel, entity, cluster).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.functions import local_clusters as local
from channelalign.sources.shared import written

REPRESENTATIVE = "subset int, channel string, slot int, f array<double>, weight double"
#: The most numbers (representatives times dimensions) that come to the driver for the global clustering; more are refused.
MOST_NUMBERS = 20_000_000
#: Points of a subset that one task clusters, about: subsets grow in number with the points, not in size.
SUBSET_POINTS = 100_000


@dataclass(frozen=True)
class ClusterSpec:
    """k clusters; w subsets or as many as hold SUBSET_POINTS points each (subsets 'per_task'), subsets of about w points ('literal'), or a number of subsets. method: kmeans, gmm or a function (points, k, seed) -> (points, weights). representative: mean, sample or moments. weight: none or count."""

    k: int = 5
    w: int = 22
    subsets: str | int = "per_task"
    method: str | Callable = "kmeans"
    representative: str = "mean"
    weight: str = "none"
    n_samples: int = 20
    rounds: int = 1
    distance: str = "euclidean"
    joint: bool = True
    nearest: int = 1
    seed: int = 7


def subset_count(spec: ClusterSpec, n_points: int) -> int:
    if spec.subsets == "per_task":
        return max(1, spec.w, -(-n_points // SUBSET_POINTS))
    return max(1, -(-n_points // spec.w)) if spec.subsets == "literal" else int(spec.subsets)


def assign_subsets(features: DataFrame, n_subsets: int, seed: int = 0, portable: bool = False) -> DataFrame:
    """features with a uniform random ``subset``. A hash of the entity decides: the same on every retry. portable uses MD5, which other engines have, too."""
    if portable:
        named = F.md5(F.concat_ws(":", "channel", F.col("entity").cast("string"), F.lit(str(seed))))
        value = F.conv(F.substring(named, 1, 8), 16, 10).cast("long")
    else:
        value = F.xxhash64("channel", "entity", F.lit(seed))
    return features.withColumn("subset", F.pmod(value, F.lit(n_subsets)).cast("int"))


def local_cluster(features: DataFrame, spec: ClusterSpec, seed: int | None = None) -> DataFrame:
    """Representatives of every (subset, channel): one group per task at a time, of about N / subsets points."""
    spec_seed = spec.seed if seed is None else seed

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        # Rows come in any order: sorted, the result does not depend on how the input was split.
        points = np.array(group.sort_values("entity")["f"].to_list(), float)
        own = spec_seed * 1_000_003 + int(key[0])
        if callable(spec.method):
            reps, weights = spec.method(points, spec.k, own)
        elif spec.representative == "moments":
            reps, weights = local.moments(points, spec.k, own, spec.n_samples)
        elif spec.method == "gmm" or spec.representative == "sample":
            reps, weights = local.mixture(points, spec.k, own, spec.n_samples)
        else:
            reps, weights = local.kmeans(points, spec.k, own, distance=spec.distance)
            if spec.weight == "none":
                weights = np.ones(len(reps))
        return pd.DataFrame({"subset": key[0], "channel": key[1], "slot": np.arange(len(reps)), "f": [list(map(float, r)) for r in reps], "weight": np.asarray(weights, float)})

    return features.select("subset", "channel", "entity", "f").groupBy("subset", "channel").applyInPandas(run, REPRESENTATIVE)


def _centres(rows: list, spec: ClusterSpec, start: np.ndarray | None = None) -> np.ndarray:
    points, weights = np.array([r["f"] for r in rows], float), np.array([r["weight"] for r in rows], float)
    centres, _ = local.kmeans(points, spec.k, spec.seed, weights, start, 200, spec.distance)
    return centres[np.lexsort(centres.T[::-1])]


def global_centroids(reps: DataFrame, spec: ClusterSpec, start: np.ndarray | None = None, most: int = MOST_NUMBERS) -> np.ndarray:
    """k centroids of the representatives of all channels together, so that labels correspond across channels.

    Representatives are k for each subset and channel and come to the driver in one job. One algorithm serves
    all sizes; more than ``most`` numbers (literal subsets on very many points) are refused, before they arrive.
    """
    width = F.max(F.size("f"))
    rows = written(reps, "representatives")
    n, d = rows.agg(F.count(F.lit(1)), width).first()
    if not n:
        raise ValueError("there are no points to cluster")
    if n * d > most:
        raise ValueError(f"{n} representatives of {d} dimensions are over {most} numbers: make fewer, larger subsets")
    return _centres(rows.orderBy("subset", "channel", "slot").collect(), spec, start)


def _distance(distance: str, centre: list[float]):
    c = F.array(*[F.lit(float(x)) for x in centre])
    add = lambda a, x: a + x
    zero = F.lit(0.0)
    if distance == "euclidean":
        return F.aggregate(F.zip_with("f", c, lambda x, y: (x - y) * (x - y)), zero, add)
    if distance == "manhattan":
        return F.aggregate(F.zip_with("f", c, lambda x, y: F.abs(x - y)), zero, add)
    if distance == "cosine":
        dot = F.aggregate(F.zip_with("f", c, lambda x, y: x * y), zero, add)
        norm = F.sqrt(F.aggregate(F.transform("f", lambda x: x * x), zero, add)) * float(np.linalg.norm(centre))
        return F.when(norm > 0, 1 - dot / norm).otherwise(1.0)
    raise ValueError(f"no distance {distance}")


def label(features: DataFrame, centroids: np.ndarray | list, distance: str = "euclidean", nearest: int = 1) -> DataFrame:
    """The nearest centroid of every entity: a projection without a shuffle. nearest > 1 gives that many labels, one row each.

    Few centroids are literals in the plan; many (k * d over 4000) are compared in an Arrow function.
    """
    centres = np.asarray(centroids, float)
    if nearest == 1 and centres.size > 4000:
        @F.pandas_udf("int")
        def closest(f: pd.Series) -> pd.Series:
            return pd.Series(local.nearest(np.array(f.to_list(), float), centres, distance).astype(np.int32))

        return features.select("channel", "entity", closest("f").alias("cluster"))
    ranked = F.array_sort(F.array(*[F.struct(_distance(distance, list(c)).alias("d"), F.lit(i).alias("i")) for i, c in enumerate(centres)]))
    if nearest == 1:
        return features.select("channel", "entity", ranked[0]["i"].alias("cluster"))
    return features.select("channel", "entity", F.explode(F.slice(ranked, 1, nearest)).alias("x")).select("channel", "entity", F.col("x.i").alias("cluster"))


def representative_clusters(features: DataFrame, spec: ClusterSpec = ClusterSpec()) -> tuple[DataFrame, np.ndarray]:
    """(labels, centroids). rounds > 1 repeats with new random subsets, each started from the last centroids."""
    n = features.count() if isinstance(spec.subsets, str) else 0
    start = None
    for r in range(spec.rounds):
        parted = assign_subsets(features, subset_count(spec, n), spec.seed + r)
        reps = local_cluster(parted, spec, spec.seed + r)
        if not spec.joint:
            return _per_channel(features, reps, spec)
        start = global_centroids(reps, spec, start if start is not None and len(start) == spec.k else None)
    return label(features, start, spec.distance, spec.nearest), start


def _per_channel(features: DataFrame, reps: DataFrame, spec: ClusterSpec) -> tuple[DataFrame, np.ndarray]:
    """Channels clustered alone; the first channel's centroids name the clusters, each centroid of another takes the nearest one's name."""
    channels = sorted(r[0] for r in reps.select("channel").distinct().collect())
    named, labels = None, None
    for c in channels:
        own = global_centroids(reps.where(F.col("channel") == c), spec)
        named = own if named is None else named
        names = local.nearest(own, named, spec.distance)
        numbered = label(features.where(F.col("channel") == c), own, spec.distance)
        renamed = numbered.withColumn("cluster", F.array(*[F.lit(int(x)) for x in names])[F.col("cluster")])
        labels = renamed if labels is None else labels.unionByName(renamed)
    return labels, named


def segment_clusters(features: DataFrame, spec: ClusterSpec = ClusterSpec()) -> DataFrame:
    """segment, channel, entity, cluster: every segment clustered by itself, all in one plan. features: segment, channel, entity, f.

    Subsets are groups of (segment, subset, channel). The segments' centroids, k each, go to the entities as one
    broadcast row a segment.
    """
    counts = features.groupBy("segment").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    subsets = subset_count(spec, counts)
    parted = assign_subsets(features, subsets, spec.seed).select(F.col("segment"), "subset", "channel", "entity", "f")

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        points = np.array(group.sort_values("entity")["f"].to_list(), float)
        reps, weights = local.kmeans(points, spec.k, spec.seed * 1_000_003 + int(key[1]), distance=spec.distance)
        return pd.DataFrame({"segment": key[0], "subset": key[1], "channel": key[2], "slot": np.arange(len(reps)), "f": [list(map(float, r)) for r in reps], "weight": np.ones(len(reps)) if spec.weight == "none" else np.asarray(weights, float)})

    reps = written(parted.groupBy("segment", "subset", "channel").applyInPandas(run, "segment long, " + REPRESENTATIVE), "representatives")
    n, d = reps.agg(F.count(F.lit(1)), F.max(F.size("f"))).first()
    if (n or 0) * (d or 0) > MOST_NUMBERS:
        raise ValueError(f"{n} representatives are over {MOST_NUMBERS} numbers: make fewer, larger subsets")
    by: dict[int, list] = {}
    for r in reps.orderBy("segment", "subset", "channel", "slot").collect():
        by.setdefault(r["segment"], []).append(r)
    table = [(segment, [list(map(float, c)) for c in _centres(rows, spec)]) for segment, rows in by.items()]
    centres = features.sparkSession.createDataFrame(table, "segment long, c array<array<double>>")
    gap = lambda c: F.aggregate(F.zip_with("f", c, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda a, x: a + x)
    nearest = F.array_sort(F.transform("c", lambda c, i: F.struct(gap(c).alias("d"), i.alias("i"))))[0]["i"]
    return features.join(F.broadcast(centres), "segment").select("segment", "channel", "entity", nearest.cast("int").alias("cluster"))


def balance(labels: DataFrame) -> DataFrame:
    """cluster, channel, n, share of its channel: uneven clusters limit what restricting comparisons can save."""
    counts = labels.groupBy("channel", "cluster").agg(F.count(F.lit(1)).alias("n"))
    totals = counts.groupBy("channel").agg(F.sum("n").alias("_all"))
    return counts.join(F.broadcast(totals), "channel").select("cluster", "channel", "n", (F.col("n") / F.col("_all")).alias("share"))


def activity_bands(binned: DataFrame, edges: tuple[int, ...]) -> DataFrame:
    """Labels by the number of an entity's events: the band that it lies in."""
    n = binned.groupBy("channel", "entity").agg(F.sum("cnt").alias("_n"))
    return n.select("channel", "entity", sum(((F.col("_n") >= e).cast("int") for e in edges), F.lit(0)).alias("cluster"))
