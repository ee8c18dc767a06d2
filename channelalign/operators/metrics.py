"""Accuracy and cost measures. found and truth have columns u and v; a measure that has nothing to divide by is null."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _share(part, whole):
    return part / F.nullif(whole, F.lit(0))


def matched_accuracy(found: DataFrame, truth: DataFrame) -> DataFrame:
    """n_found, n_wrong, wrong_share, ma: share of matches that are not in truth, and one minus it."""
    t = truth.select("u", "v").distinct().withColumn("_t", F.lit(1))
    row = found.select("u", "v").distinct().join(t, ["u", "v"], "left").agg(F.count(F.lit(1)).alias("n_found"), F.count_if(F.col("_t").isNull()).alias("n_wrong"))
    return row.withColumn("wrong_share", _share(F.col("n_wrong"), F.col("n_found"))).withColumn("ma", 1 - F.col("wrong_share"))


def not_matched(found: DataFrame, truth: DataFrame, side: str = "forward", unit: str = "entity") -> DataFrame:
    """n_true, n_missed, missed_share, accuracy: true matches that were not found. unit entity counts entities of the side (u forward, v backward) with a true partner, found if any of its matches is right; unit pair counts pairs."""
    by = {"forward": "u", "backward": "v"}[side]
    hit = truth.select("u", "v").distinct().join(found.select("u", "v").distinct().withColumn("_f", F.lit(1)), ["u", "v"], "left")
    if unit == "entity":
        hit = hit.groupBy(by).agg(F.max("_f").alias("_f"))
    row = hit.agg(F.count(F.lit(1)).alias("n_true"), F.count_if(F.col("_f").isNull()).alias("n_missed"))
    return row.withColumn("missed_share", _share(F.col("n_missed"), F.col("n_true"))).withColumn("accuracy", 1 - F.col("missed_share"))


def summary(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: n_found, n_right, n_true, ma, fnma, bnma, precision, recall, f1, jaccard."""
    both = found.select("u", "v").distinct().withColumn("_f", F.lit(1)).join(truth.select("u", "v").distinct().withColumn("_t", F.lit(1)), ["u", "v"], "full")
    return _summed(both.select("u", "v", "_f", "_t"))


def _summed(both: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    right = F.col("_f").isNotNull() & F.col("_t").isNotNull()
    by_u = both.groupBy(*keys, "u").agg(F.count("_f").alias("f"), F.count("_t").alias("t"), F.count_if(right).alias("r"))
    us = by_u.groupBy(*keys).agg(F.sum("f").alias("n_found"), F.sum("t").alias("n_true"), F.sum("r").alias("n_right"), F.count_if(F.col("t") > 0).alias("tu"), F.count_if(F.col("r") > 0).alias("ru"))
    by_v = both.groupBy(*keys, "v").agg(F.count("_t").alias("t"), F.count_if(right).alias("r"))
    vs = by_v.groupBy(*keys).agg(F.count_if(F.col("t") > 0).alias("tv"), F.count_if(F.col("r") > 0).alias("rv"))
    row = us.join(vs, list(keys)) if keys else us.crossJoin(vs)
    p, r = _share(F.col("n_right"), F.col("n_found")), _share(F.col("n_right"), F.col("n_true"))
    return row.select(
        *keys, F.coalesce("n_found", F.lit(0)).alias("n_found"), F.coalesce("n_right", F.lit(0)).alias("n_right"), F.coalesce("n_true", F.lit(0)).alias("n_true"),
        p.alias("ma"), _share(F.col("ru"), F.col("tu")).alias("fnma"), _share(F.col("rv"), F.col("tv")).alias("bnma"),
        r.alias("recall"), _share(2 * F.col("n_right"), F.col("n_found") + F.col("n_true")).alias("f1"),
        _share(F.col("n_right"), F.col("n_found") + F.col("n_true") - F.col("n_right")).alias("jaccard"),
    )


def jaccard(found: DataFrame, truth: DataFrame) -> DataFrame:
    """n_both, n_either, jaccard of the two pair sets."""
    f, t = found.select("u", "v").distinct(), truth.select("u", "v").distinct()
    both = f.intersect(t).agg(F.count(F.lit(1)).alias("n_both"))
    either = f.union(t).distinct().agg(F.count(F.lit(1)).alias("n_either"))
    return both.crossJoin(either).withColumn("jaccard", _share(F.col("n_both"), F.col("n_either")))


def correct_count(found: DataFrame, truth: DataFrame) -> DataFrame:
    """n_entities: left entities with a right match; n_pairs."""
    right = found.select("u", "v").distinct().join(truth.select("u", "v").distinct(), ["u", "v"], "left_semi")
    return right.agg(F.countDistinct("u").alias("n_entities"), F.count(F.lit(1)).alias("n_pairs"))


def sweep(state: DataFrame, truth: DataFrame, thetas: list[float], score: str = "score", rule: str = "best", keys: tuple[str, ...] = ()) -> DataFrame:
    """A row for each threshold: the measures of summary() for the matches of at least that score, found in both directions.

    All thresholds are read from one pass: a pair is a mutual best of those above a threshold exactly if it is a
    mutual best of all and itself above, so pairs are ranked once and thresholds join matches and truth only.
    """
    from channelalign.operators.matching import reconcile

    if rule not in ("best", "threshold"):
        raise ValueError("thresholds nest for the rules best and threshold only")
    found = reconcile(state, rule=rule, score=score).select("u", "v", F.col(score).alias("_s")).distinct()
    grid = state.sparkSession.createDataFrame([(float(x),) for x in thetas], "theta double")
    both = found.withColumn("_f", F.lit(1)).join(truth.select("u", "v").distinct().withColumn("_t", F.lit(1)), ["u", "v"], "full")
    at = both.crossJoin(F.broadcast(grid)).select("theta", "u", "v", F.when(F.col("_s") >= F.col("theta"), F.col("_f")).alias("_f"), "_t").where("_f IS NOT NULL OR _t IS NOT NULL")
    return _summed(at, ("theta",))


def comparisons(labels: DataFrame, left: str, right: str) -> DataFrame:
    """One row: kept (entity pairs of equal cluster), all_pairs, kept_share, ideal_speed_up."""
    sizes = labels.groupBy("cluster").agg(F.count_if(F.col("channel") == left).alias("a"), F.count_if(F.col("channel") == right).alias("b"))
    row = sizes.agg(F.sum(F.col("a") * F.col("b")).alias("kept"), (F.sum("a") * F.sum("b")).alias("all_pairs"))
    return row.withColumn("kept_share", _share(F.col("kept"), F.col("all_pairs"))).withColumn("ideal_speed_up", _share(F.col("all_pairs"), F.col("kept")))


def partial_products(binned: DataFrame, left: str, right: str, labels: DataFrame | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """One row: products, the rows that the similarity join makes; busiest, the most of one bin."""
    rows, on = binned.where(F.col("channel").isin(left, right)), [*keys, "bin"]
    if labels is not None:
        by = [*[k for k in keys if k in labels.columns], "channel", "entity"]
        rows, on = rows.join(labels.select(*by, "cluster"), by), [*on, "cluster"]
    sides = rows.groupBy(*on).agg(F.count_if(F.col("channel") == left).alias("a"), F.count_if(F.col("channel") == right).alias("b"))
    product = F.col("a") * F.col("b")
    return sides.agg(F.coalesce(F.sum(product), F.lit(0)).alias("products"), F.coalesce(F.max(product), F.lit(0)).alias("busiest"), F.count_if(product > 0).alias("shared_bins"))


def cocluster_recall(labels: DataFrame, truth: DataFrame, left: str, right: str) -> DataFrame:
    """n_true, n_together, recall: true pairs whose entities have the same cluster; bounds what clustering leaves to find."""
    a = labels.where(F.col("channel") == left).select(F.col("entity").alias("u"), F.col("cluster").alias("cu"))
    b = labels.where(F.col("channel") == right).select(F.col("entity").alias("v"), F.col("cluster").alias("cv"))
    row = truth.select("u", "v").distinct().join(a, "u").join(b, "v").agg(F.count(F.lit(1)).alias("n_true"), F.count_if(F.col("cu") == F.col("cv")).alias("n_together"))
    return row.withColumn("recall", _share(F.col("n_together"), F.col("n_true")))


def clustering_quality(features: DataFrame, labels: DataFrame, gold: DataFrame) -> DataFrame:
    """One row: inertia (squared distance to the own cluster's mean), purity and adjusted_rand against gold (channel, entity, label)."""
    f = features.join(labels.select("channel", "entity", "cluster"), ["channel", "entity"])
    long = f.select("channel", "entity", "cluster", F.posexplode("f").alias("d", "x"))
    inertia = long.groupBy("cluster", "d").agg((F.sum(F.col("x") * F.col("x")) - F.sum("x") * F.sum("x") / F.count(F.lit(1))).alias("w")).agg(F.sum("w").alias("inertia"))
    table = labels.select("channel", "entity", "cluster").join(gold.select("channel", "entity", "label"), ["channel", "entity"]).groupBy("cluster", "label").agg(F.count(F.lit(1)).alias("n"))
    two = lambda c: (c * (c - 1) / 2).cast("double")
    rows = table.groupBy("cluster").agg(F.sum("n").alias("n"), F.max("n").alias("top"))
    per_row = rows.agg(F.sum(two(F.col("n"))).alias("ra"), F.sum("top").alias("top"), F.sum("n").alias("all"))
    per_col = table.groupBy("label").agg(F.sum("n").alias("n")).agg(F.sum(two(F.col("n"))).alias("rb"))
    cells = table.agg(F.sum(two(F.col("n"))).alias("rc"))
    expected = F.col("ra") * F.col("rb") / two(F.col("all"))
    return inertia.crossJoin(per_row).crossJoin(per_col).crossJoin(cells).select("inertia", (F.col("top") / F.col("all")).alias("purity"), _share(F.col("rc") - expected, (F.col("ra") + F.col("rb")) / 2 - expected).alias("adjusted_rand"))


def timed(frame: DataFrame) -> float:
    """Seconds in which a frame is computed in full and thrown away."""
    began = time.perf_counter()
    frame.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began
