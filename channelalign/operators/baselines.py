"""What the methods are compared with."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from channelalign.operators.cluster import label


def _vectors(features: DataFrame) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return features.select("channel", "entity", "f", array_to_vector("f").alias("features"))


def direct_kmeans(features: DataFrame, k: int, seed: int = 7) -> tuple[DataFrame, np.ndarray]:
    """K-means on all points, pass after pass."""
    from pyspark.ml.clustering import KMeans

    centres = np.array(KMeans(k=k, seed=seed, maxIter=50).fit(_vectors(features)).clusterCenters())
    return label(features, centres), centres


def direct_gmm(features: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """A Gaussian mixture on all points; the likeliest component is the label."""
    from pyspark.ml.clustering import GaussianMixture

    rows = _vectors(features)
    return GaussianMixture(k=k, seed=seed, maxIter=50).fit(rows).transform(rows).select("channel", "entity", F.col("prediction").alias("cluster"))


def sample_then_label(features: DataFrame, k: int, fraction: float = 0.1, seed: int = 7) -> tuple[DataFrame, np.ndarray]:
    """K-means on a hash sample, then labels for all."""
    from pyspark.ml.clustering import KMeans

    sample = features.where(F.pmod(F.xxhash64("channel", "entity", F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000))
    centres = np.array(KMeans(k=k, seed=seed, maxIter=50).fit(_vectors(sample)).clusterCenters())
    return label(features, centres), centres


def random_match(left: DataFrame, right: DataFrame, seed: int = 0) -> DataFrame:
    """u, v: the entities of both sides, paired in MD5 order. left has u, right v. A baseline for reports: the order is one window over each side's ids."""
    def ranked(ids: DataFrame, c: str) -> DataFrame:
        return ids.select(c).distinct().withColumn("_r", F.row_number().over(Window.orderBy(F.md5(F.concat_ws(":", F.col(c).cast("string"), F.lit(str(seed)))))))

    return ranked(left, "u").join(ranked(right, "v"), "_r").select("u", "v")


def dense_cosine(vectors: DataFrame, left: str, right: str, n_bins: int) -> DataFrame:
    """u, v, dot, sim by brute force over dense arrays, for checks on tiny data."""
    def dense(side: str, name: str) -> DataFrame:
        cells = F.map_from_arrays("bins", "cnts")
        return vectors.where(F.col("channel") == side).select(F.col("entity").alias(name), F.transform(F.sequence(F.lit(0).cast("long"), F.lit(n_bins - 1).cast("long")), lambda b: F.coalesce(F.element_at(cells, b), F.lit(0).cast("long"))).alias(f"_{name}"))

    add = lambda a, x: a + x
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), add)
    pairs = dense(left, "u").crossJoin(dense(right, "v"))
    return pairs.select("u", "v", dot("_u", "_v").alias("dot"), (dot("_u", "_v") / F.sqrt((dot("_u", "_u") * dot("_v", "_v")).cast("double"))).alias("sim")).where("dot > 0")
